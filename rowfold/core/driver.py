"""Iteration by a thin driver: one job a round, the state's log, and stop rules."""

from __future__ import annotations

import gc
import tempfile
import time
import uuid
from collections.abc import Callable
from dataclasses import dataclass, field
from typing import Any

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share: spark.checkpoint.dir, or a temporary one where none is set (tests)."""
    held = spark.sparkContext._jsc.sc().getCheckpointDir()
    if held.isDefined():
        return held.get()
    spark.sparkContext.setCheckpointDir(spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="rowfold-"))
    return spark.sparkContext._jsc.sc().getCheckpointDir().get()


def stage(df: DataFrame, name: str = "stage") -> DataFrame:
    """A new version of a large state: written once to the shared folder and read back, which cuts its lineage and
    survives lost executors."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def drop_stage(df: DataFrame) -> None:
    """Remove staged versions that a newer one, already written, takes the place of."""
    spark = df.sparkSession
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
        if folder.startswith(shared_dir(spark)):
            path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def release(spark: SparkSession) -> None:
    """Let go of the shuffle files of finished steps, which else waits for the driver's heap to fill."""
    for _ in range(2):  # what the first round frees may hold more
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        time.sleep(0.3)


@dataclass
class IterationLog:
    """One row per round: its number, what was measured and, if wanted, the state."""

    rows: list[dict] = field(default_factory=list)

    def append(self, iteration: int, **measures: float) -> None:
        self.rows.append({"iteration": iteration, **measures})

    def last(self, k: int = 1) -> list[dict]:
        return self.rows[-k:]

    def frame(self, spark: SparkSession) -> DataFrame:
        names = list(dict.fromkeys(k for r in self.rows for k in r))
        kinds = ", ".join(f"`{n}` {'int' if n == 'iteration' else 'double'}" for n in names)
        return spark.createDataFrame([tuple(r.get(n) if n == "iteration" or r.get(n) is None else float(r[n]) for n in names) for r in self.rows], kinds)


@dataclass
class FitResult:
    state: Any
    log: IterationLog
    iterations: int
    converged: bool
    frame: DataFrame | None = None


def relative_change(key: str, tol: float) -> Callable[[IterationLog], bool]:
    def stop(log: IterationLog) -> bool:
        if len(log.rows) < 2:
            return False
        a, b = log.rows[-2][key], log.rows[-1][key]
        return abs(a - b) <= tol * max(1.0, abs(b))

    return stop


def below(key: str, tol: float) -> Callable[[IterationLog], bool]:
    return lambda log: bool(log.rows) and log.rows[-1][key] <= tol


def any_of(*rules: Callable[[IterationLog], bool]) -> Callable[[IterationLog], bool]:
    return lambda log: any(r(log) for r in rules)


def iterate(state: Any, step: Callable[[Any, int], tuple[Any, dict]], stop: Callable[[IterationLog], bool], max_iter: int) -> FitResult:
    """Repeat step(state, round) -> (state, measures) until `stop` holds of the log or max_iter rounds are done."""
    log = IterationLog()
    for i in range(1, max_iter + 1):
        state, measures = step(state, i)
        log.append(i, **measures)
        if stop(log):
            return FitResult(state, log, i, True)
    return FitResult(state, log, max_iter, False)


def counted_iterations(spark: SparkSession, n: int, build: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """All rounds of a counted iteration at once: `build` gets the virtual table of round numbers (column trial)."""
    return build(spark.range(n).select(F.col("id").cast("int").alias("trial")))


def windowed_fold(df: DataFrame, by: str, order: str, value: str, init: float, step: Callable, out: str = "state") -> DataFrame:
    """The state after each row of a key's ordered rows: an ordered list and running array folds inside one row per
    key, so keys should be small. step(state column, value column) gives the next state."""
    rows = df.groupBy(by).agg(F.sort_array(F.collect_list(F.struct(F.col(order).alias("o"), F.col(value).cast("double").alias("v")))).alias("rows"))
    states = F.aggregate("rows", F.array(F.lit(float(init))), lambda acc, r: F.concat(acc, F.array(step(F.element_at(acc, -1), r["v"]))))
    return rows.select(by, F.posexplode(F.arrays_zip(F.col("rows").alias("r"), F.slice(states, F.lit(2), F.size("rows")).alias("s"))).alias("pos", "z")).select(by, F.col("z.r.o").alias(order), F.col("z.r.v").alias(value), F.col("z.s").alias(out))


def recursive(spark: SparkSession, name: str, columns: list[str], seed_sql: str, step_sql: str, max_level: int = 100) -> DataFrame:
    """A recursive query: `step_sql` reads `name`. Levels are limited; each is a job of its own, so this suits short
    chains only."""
    limited = f"WITH RECURSIVE {name}({', '.join(columns)}) MAX RECURSION LEVEL {int(max_level)} AS ({seed_sql} UNION ALL {step_sql}) SELECT * FROM {name}"
    return spark.sql(limited)

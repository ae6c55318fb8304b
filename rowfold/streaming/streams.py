"""Folds kept up to date over micro-batches, windows with late data, and state per key.

Event times are cast to TIMESTAMP first, since a watermark takes no other type.
"""

from __future__ import annotations

import pickle
import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from rowfold.core.driver import drop_stage, shared_dir
from rowfold.core.fold import Fold, _merged, partial_states


def source(spark: SparkSession, path: str, schema, files_per_batch: int = 1, fmt: str = "parquet") -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).format(fmt).load(path)


def stamped(df: DataFrame, ts: str, late: str | None = None) -> DataFrame:
    out = df.withColumn(ts, F.col(ts).cast("timestamp"))
    return out.withWatermark(ts, late) if late else out


class FoldStore:
    """States by batch number: a batch that is run again replaces its own state, so results do not count it twice. States
    are of the size of the model; those of finished batches are merged into one."""

    def __init__(self, fold: Fold):
        self.fold, self.base, self.upto, self.last = fold, None, -1, None

    def put(self, batch: int, state) -> None:
        if batch > self.upto and self.last is not None:
            self.base = self.fold.merge(self.base if self.base is not None else self.fold.zero(), self.last)
        self.upto, self.last = batch, state

    def result(self) -> list[dict]:
        both = self.fold.merge(self.base if self.base is not None else self.fold.zero(), self.last if self.last is not None else self.fold.zero())
        return self.fold.finish(both)


def fold(sdf: DataFrame, f: Fold, cols: list[str], checkpoint: str, slots: int = 4) -> tuple[StreamingQuery, FoldStore]:
    """Fold each micro-batch and merge it with what came before. The answer equals the batch answer over all rows."""
    store = FoldStore(f)

    def batch(df: DataFrame, number: int) -> None:
        level = partial_states(df.select(*cols), f, slots)
        store.put(number, _merged([r["state"] for r in level.select("state").collect()], f))  # one state a partition

    q = sdf.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    return q, store


def tumbling(sdf: DataFrame, ts: str, size: str, aggs: list, by: tuple[str, ...] = (), slide: str | None = None) -> DataFrame:
    w = F.window(ts, size, slide) if slide else F.window(ts, size)
    return sdf.groupBy(w.alias("w"), *by).agg(*aggs).select(F.col("w.start").alias("start"), *by, *[c for c in _names(aggs)])


def sessions(sdf: DataFrame, ts: str, gap: str, key: str, aggs: list) -> DataFrame:
    return sdf.groupBy(F.session_window(ts, gap).alias("w"), key).agg(*aggs).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), key, *_names(aggs))


def _names(aggs: list) -> list[str]:
    return [a._jc.toString().rsplit(" AS ", 1)[-1].strip("`") for a in aggs]


def keyed(sdf: DataFrame, key: str, value: str, init: dict, update: Callable[[dict, pd.Series], dict], out_schema: str) -> DataFrame:
    """State of any shape for each key, kept as bytes; `update` sees a micro-batch's values of the key. One row per key and
    batch with the state's fields."""
    names = [p.split()[0] for p in out_schema.split(",")]

    def work(k, frames: Iterator[pd.DataFrame], state):
        own = pickle.loads(state.get[0]) if state.exists else dict(init)
        for f in frames:
            own = update(own, f[value])
        state.update((pickle.dumps(own),))
        yield pd.DataFrame([{key: k[0], **own}])[[key, *names]]

    kind = dict(sdf.dtypes)[key]
    return sdf.select(key, value).groupBy(key).applyInPandasWithState(work, f"{key} {kind}, {out_schema}", "s binary", "update", "NoTimeout")


def dedup(sdf: DataFrame, keys: list[str]) -> DataFrame:
    return sdf.dropDuplicatesWithinWatermark(keys)


def interval_join(left: DataFrame, right: DataFrame, key: str, lts: str, rts: str, within: str) -> DataFrame:
    """Rows of right that follow a row of left with the same key within the interval; both sides carry watermarks."""
    r = right.withColumnRenamed(key, f"r_{key}")
    return left.join(r, (F.col(key) == F.col(f"r_{key}")) & (F.col(rts) >= F.col(lts)) & (F.col(rts) <= F.col(lts) + F.expr(f"interval {within}")))


def drained(df: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there into a memory table; for tests and small results."""
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name)


def summed(df: DataFrame, summary: Callable[[DataFrame], DataFrame], checkpoint: str) -> DataFrame:
    """Run a stream over all that is there in complete mode and return a summary of its last result, as files of the shared
    folder. Each batch's whole result is summed up in the tasks that hold the state, so no row of it comes to the driver."""
    spark, root, schema = df.sparkSession, f"{shared_dir(df.sparkSession)}/summed-{uuid.uuid4().hex}", summary(df).schema
    done: dict[int, DataFrame] = {}

    def batch(result: DataFrame, number: int) -> None:
        path = f"{root}/{number}"
        summary(result).write.mode("overwrite").parquet(path)  # a batch that is run again replaces its own
        done[number] = spark.read.schema(schema).parquet(path)
        for old in [k for k in done if k < number]:
            drop_stage(done.pop(old))

    q = df.writeStream.foreachBatch(batch).outputMode("complete").option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return done[max(done)] if done else spark.createDataFrame([], schema)

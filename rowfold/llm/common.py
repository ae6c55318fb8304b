"""Helpers shared by the training-data operators."""

from __future__ import annotations

import gc
import re
import tempfile
import time
import uuid
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir, or one of our own where it is unset (tests)."""
    sc = spark.sparkContext
    held = sc._jsc.sc().getCheckpointDir()
    if held.isDefined():
        return held.get()
    base = spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="rowfold-")
    sc.setCheckpointDir(base)
    return sc._jsc.sc().getCheckpointDir().get()


def staged(df: DataFrame, what: str) -> DataFrame:
    """Write ``df`` once as Parquet in the shared folder and read it back: lineage is cut, and several readers
    cost one evaluation. Survives lost executors, unlike a cache."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{what}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def steady(df: DataFrame, what: str) -> DataFrame:
    """``df`` if its rows come straight from files, so that reading it twice gives the same rows in the same order; else a
    staged copy, since what comes through a shuffle or a cache may come in another order the next time."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    return staged(df, what) if re.search(r"(?<!Broadcast)Exchange|InMemoryTableScan", plan) else df


def release(spark: SparkSession) -> None:
    """Let go of the shuffle files of finished steps now: Spark's cleaner drops them once the plans that made them have
    been collected, which otherwise waits for the driver's heap to fill."""
    for _ in range(2):  # what the first round frees may hold more
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        time.sleep(0.3)


def parts_for(df: DataFrame, total_bytes: int, target: int) -> int:
    """Partitions so that each gets about ``target`` bytes, and at least the session's shuffle partitions."""
    least = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return max(least, -(-int(total_bytes) // target), 1)


def text_bytes(df: DataFrame, text: str = "text") -> int:
    return df.agg(F.coalesce(F.sum(F.octet_length(text)), F.lit(0)).alias("b")).first()["b"]


def utf8(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column: the bytes are not copied; nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    _, off, data = column.buffers()
    kind = np.int64 if pa.types.is_large_string(column.type) else np.int32
    offsets = np.frombuffer(off, kind)[column.offset : column.offset + len(column) + 1].astype(np.int64) if off is not None and len(column) else np.zeros(1, np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw, offsets


def slices(batches: Iterable[pa.RecordBatch], column: int, most: int) -> Iterator[pa.RecordBatch]:
    """Cut batches so that the text of each is at most ``most`` bytes, or a single row."""
    for batch in batches:
        _, off = utf8(batch.column(column))
        at, n = 0, batch.num_rows
        while at < n:
            to = max(at + 1, int(np.searchsorted(off, off[at] + most, side="right")) - 1)
            yield batch.slice(at, min(to, n) - at)
            at = to


def spans_text(spans: list[tuple[int, int, int]], kinds: tuple[str, ...]) -> str:
    """kind:start:end by start, then by the kind's place in ``kinds``."""
    return ",".join(f"{kinds[k]}:{s}:{e}" for s, k, e in sorted(spans))

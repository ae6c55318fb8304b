"""Contiguous balanced shards from global byte-size prefix sums.

Rows are range-partitioned by id and sorted; each partition scans itself once and
leaves running byte and row counts. Only one total per partition is added up
globally; a row's global offset is its partition's offset plus its own, and its
shard is where that offset falls among equal byte targets.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rowfold.llm.common import staged


def _running(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Add the partition number and the bytes and rows before each row; holds one batch at a time."""
    part, rows, size = TaskContext.get().partitionId(), 0, 0
    for b in batches:
        own = b.column("size").to_numpy(zero_copy_only=False)
        upto = np.cumsum(own) + size
        n = b.num_rows
        yield pa.RecordBatch.from_arrays(
            [*b.columns, pa.array(np.full(n, part, np.int32)), pa.array(np.arange(rows, rows + n)), pa.array(upto - own)],
            names=[*b.schema.names, "part", "rows_before", "bytes_before"],
        )
        rows, size = rows + n, int(upto[-1]) if n else size


def shard_by_bytes(df: DataFrame, shards: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, size, text_crc32, law, shard, slot, grown_shard, global_offset.

    size is the text's UTF-8 bytes plus 1; a null text has no bytes (size 1, CRC of nothing, 0). A null id
    sorts first. Rows that repeat an id are kept, ordered by size and CRC. An empty table gives no rows.
    Other columns of ``df`` are ignored, whatever their names. A row belongs to the shard in which its first
    byte falls, so shards differ from the equal target by less than one row.
    """
    raw = F.coalesce(F.col(text_col).cast("binary"), F.lit(b""))
    rows = df.select(F.col(id_col), (F.octet_length(raw) + 1).cast("long").alias("size"), F.crc32(raw).alias("text_crc32"))
    order = [F.col(id_col).asc_nulls_first(), "size", "text_crc32"]
    dealt = rows.repartitionByRange(*order).sortWithinPartitions(*order)
    schema = f"{id_col} {dict(rows.dtypes)[id_col]}, size long, text_crc32 long, part int, rows_before long, bytes_before long"
    local = staged(dealt.mapInArrow(_running, schema), "shard-rows")
    totals = local.groupBy("part").agg(F.count("*").alias("n"), F.sum("size").alias("b"))  # one row per partition
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = totals.select(
        "part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("row0"), F.coalesce(F.sum("b").over(before), F.lit(0)).alias("byte0"),
        F.sum("b").over(Window.partitionBy()).alias("total"),
    )
    placed = local.join(F.broadcast(offsets), "part").select(
        id_col, "size", "text_crc32", (F.col("row0") + F.col("rows_before")).alias("row"), (F.col("byte0") + F.col("bytes_before")).alias("global_offset"), "total",
    ).withColumn("shard", F.expr(f"cast(global_offset * {int(shards)} div total as int)"))
    first = placed.groupBy("shard").agg(F.min("row").alias("row_first"))  # at most `shards` rows
    return placed.join(F.broadcast(first), "shard").select(
        id_col, "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("row") - F.col("row_first")).alias("slot"), F.lit(None).cast("int").alias("grown_shard"), "global_offset",
    )

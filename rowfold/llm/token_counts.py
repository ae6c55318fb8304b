"""Tokens of each document of flat token files, found by their separators alone.

A flat file is a stream of little-endian 16-bit ids in which an end-of-document
id closes every document; there is no index. It is stored in blocks of equal
length that pay no heed to documents. One vectorised search for the separator
in each block gives its separators' places; blocks then need only two numbers of
those before them, added up by a prefix scan over one row per block: how many
documents have ended, and how many tokens of an unfinished one are left over.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rowfold.llm.common import slices, staged
from rowfold.llm.pieces import encode_batch, load_pieces

BLOCK = "stream int, block int, kind string, data binary"


def write_flat(docs: DataFrame, model_file: str, eos: int = 2, block_tokens: int = 1 << 20, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Encode every text into flat streams, one for each input partition, and store them in the shared folder.

    Rows of kind "tokens" hold blocks of exactly block_tokens ids (the last may be shorter); rows of kind "order"
    hold the ids of the documents of a stream in order, 64 bits each, in blocks of their own. The streams say
    nothing about where documents begin. `eos` must not be an id that encoding gives, and ids must be below 65,536.
    A null id is kept as the least 64-bit number.
    """
    p = load_pieces(model_file)
    if len(p.utf8) > 1 << 16 or p.utf8[eos]:
        raise ValueError("ids must fit 16 bits, and the separator must be a control piece")
    shipped = docs.sparkSession.sparkContext.broadcast(p)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        stream = TaskContext.get().partitionId()
        held, size, block = [], 0, 0
        order = 0

        def row(at: int, kind: str, data: np.ndarray) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([stream], pa.int32()), pa.array([at], pa.int32()), pa.array([kind]), pa.array([data.tobytes()], pa.binary())], names=["stream", "block", "kind", "data"])

        for b in slices(batches, 1, 4 << 20):
            ids, counts = encode_batch(b.column(1), shipped.value)
            ends = np.cumsum(counts)
            flat = np.insert(ids, ends, eos).astype("<u2")
            yield row(order, "order", b.column(0).cast(pa.int64()).fill_null(-(1 << 63)).to_numpy(zero_copy_only=False).astype("<i8"))
            order += 1
            held.append(flat)
            size += len(flat)
            while size >= block_tokens:
                flat = np.concatenate(held)
                yield row(block, "tokens", flat[:block_tokens])
                block += 1
                held, size = [flat[block_tokens:]], size - block_tokens
        if size:
            yield row(block, "tokens", np.concatenate(held))

    return staged(docs.select(id_col, text_col).mapInArrow(work, BLOCK), "flat-tokens")


def scan_blocks(blocks: DataFrame, eos: int) -> DataFrame:
    """(stream, block, n, ends, seps, last) for token blocks (stream, block, data): n tokens in the block, the places
    of its separators as a binary of 32-bit numbers, their number and the last. One vectorised comparison a block."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n, ends, seps, last = [], [], [], []
            for data in b.column(2):
                tokens = np.frombuffer(data.as_buffer(), "<u2")
                n.append(len(tokens))
                at = np.flatnonzero(tokens == eos)
                ends.append(at.astype("<i4").tobytes())
                seps.append(len(at))
                last.append(int(at[-1]) if len(at) else None)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(n, pa.int64()), pa.array(ends, pa.binary()), pa.array(seps, pa.int64()), pa.array(last, pa.int64())], names=["stream", "block", "n", "ends", "seps", "last"])

    return blocks.select("stream", "block", "data").mapInArrow(work, "stream int, block int, n long, ends binary, seps long, last long")


def count_tokens(blocks: DataFrame, eos: int = 2) -> DataFrame:
    """(stream, ordinal, n_tokens): tokens of each document of each stream, without its separator.

    blocks: (stream, block, data). A stream that doesn't end with a separator has a last, unfinished document,
    which is counted if it has tokens. Empty blocks and streams give nothing; two separators side by side are an
    empty document. The prefix scan is over one row per block, dealt by stream.
    """
    found = scan_blocks(blocks, eos)
    w = Window.partitionBy("stream").orderBy("block")
    upto = w.rowsBetween(Window.unboundedPreceding, -1)
    place = (
        found.withColumn("base", F.coalesce(F.sum("n").over(upto), F.lit(0)))
        .withColumn("docs_before", F.coalesce(F.sum("seps").over(upto), F.lit(0)))
        .withColumn("end_abs", F.col("base") + F.col("last"))
        .withColumn("prev_end", F.coalesce(F.max("end_abs").over(upto), F.lit(-1)))
        .withColumn("is_last", F.lead("block").over(w).isNull())
    )

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for stream, n, ends, base, before, prev, final in zip(*(b.column(i) for i in range(7))):
                at = np.frombuffer(ends.as_buffer(), "<i4").astype(np.int64) + base.as_py()
                if final.as_py():
                    stop = base.as_py() + n.as_py()
                    if stop - 1 > (at[-1] if len(at) else prev.as_py()):
                        at = np.append(at, stop)
                counts = np.diff(at, prepend=prev.as_py()) - 1
                k = len(counts)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(k, stream.as_py(), np.int32)), pa.array(np.arange(k) + before.as_py()), pa.array(counts)], names=["stream", "ordinal", "n_tokens"])

    return place.select("stream", "n", "ends", "base", "docs_before", "prev_end", "is_last").mapInArrow(work, "stream int, ordinal long, n_tokens long")


def documents_of(order: DataFrame) -> DataFrame:
    """(stream, ordinal, doc_id) from the order blocks."""
    w = Window.partitionBy("stream").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    placed = order.select("stream", "data", F.coalesce(F.sum(F.length("data") / 8).over(w), F.lit(0)).cast("long").alias("base"))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for stream, data, base in zip(*b.columns):
                ids = np.frombuffer(data.as_buffer(), "<i8")
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(ids), stream.as_py(), np.int32)), pa.array(np.arange(len(ids)) + base.as_py()), pa.array(ids, mask=ids == -(1 << 63))], names=["stream", "ordinal", "doc_id"])

    return placed.mapInArrow(work, "stream int, ordinal long, doc_id long")


def tokens_by_document(docs: DataFrame, model_file: str, eos: int = 2) -> DataFrame:
    """One row per input row: doc_id, n_tokens. Written as flat streams first, then counted from the streams.

    A null or empty text has 0 tokens; repeated or null doc_ids keep their rows; an empty table gives none.
    """
    flat = write_flat(docs, model_file, eos)
    counts = count_tokens(flat.filter("kind = 'tokens'").select("stream", "block", "data"), eos)
    return documents_of(flat.filter("kind = 'order'")).join(counts, ["stream", "ordinal"]).select("doc_id", "n_tokens")


def read_flat_files(spark, path: str, block_bytes: int = 2 << 20) -> DataFrame:
    """Blocks of real flat files of 16-bit ids; each file is a stream of its own.

    Spark hands a whole file to a task, so files must be below 2 GB and fit a worker's memory; a task cuts its file into
    blocks of block_bytes at once. Streams that this module writes lie in Parquet in blocks and have no such bound.
    """
    files = spark.read.format("binaryFile").load(path).select("path", "content")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for path, data in zip(*b.columns):
                raw = data.as_buffer()
                for k, at in enumerate(range(0, raw.size, block_bytes)):
                    yield pa.RecordBatch.from_arrays([pa.array([path.as_py()]), pa.array([k], pa.int32()), pa.array([raw.slice(at, min(block_bytes, raw.size - at)).to_pybytes()], pa.binary())], names=["file", "block", "data"])

    cut = files.mapInArrow(work, "file string, block int, data binary")
    names = files.select("path").distinct().select(F.col("path").alias("file"), (F.row_number().over(Window.orderBy("path")) - 1).cast("int").alias("stream"))  # one row per file
    return cut.join(names, "file").select("stream", "block", "data", "file")

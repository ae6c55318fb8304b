"""Exact top-k inner products by block-at-a-time pruning.

Vectors are turned into integers and cut into blocks of neighbouring ids. A block
keeps a forward index (its rows, by dimension) and the largest and smallest value
of each dimension. For a query, the dimension-wise maxima of its products with a
block's extremes add up to a bound on every score of the block. Blocks are taken
in order of falling bound and scored until the next bound is below the k-th score.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

SAFE = float(2**53)


def quantise(df: DataFrame, scale: int, id_col: str, vec_col: str) -> DataFrame:
    """(vec_id, v array<long>): floor(scale * x) of each component, for vectors that are null-free and finite."""
    x = F.col(vec_col).cast("array<double>")
    good = x.isNotNull() & ~F.exists(x, lambda c: c.isNull() | F.isnan(c) | (F.abs(c) == float("inf")))
    return df.filter(F.col(id_col).isNotNull() & good).select(F.col(id_col).cast("long").alias("vec_id"), F.transform(x, lambda c: F.floor(c * F.lit(float(scale)))).alias("v"))


def _matrix(column: pa.ChunkedArray, width: int) -> np.ndarray:
    """Rows of integers; short vectors are filled with zeros, which add nothing to an inner product."""
    col = column.combine_chunks()
    if isinstance(col, pa.ChunkedArray):
        col = col.chunk(0) if col.num_chunks else pa.array([], column.type)
    off = np.asarray(col.offsets)
    size = np.diff(off)
    flat = np.asarray(col.values)[off[0] : off[-1]].astype(np.float64)
    out = np.zeros((len(size), width))
    if len(size) and (size == width).all():
        return flat.reshape(len(size), width)
    out[np.arange(width) < size[:, None]] = flat
    return out


def best_of_blocks(queries: np.ndarray, qid: np.ndarray, rows: np.ndarray, ids: np.ndarray, block: int, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """(query number, vec_id, score) of each query's k best rows, and how many blocks were scored.

    rows are in order of id. Scores are exact: products of integers below 2**53 in double precision, or of Python
    integers where they are larger.
    """
    big = float(np.abs(queries).max(initial=0) * np.abs(rows).max(initial=0) * max(1, rows.shape[1])) >= SAFE
    if big:
        as_int = np.vectorize(int, otypes=[object])
        queries, rows = as_int(queries), as_int(rows)
    cuts = list(range(0, len(rows), block))
    top = np.stack([rows[a : a + block].max(axis=0) for a in cuts])
    low = np.stack([rows[a : a + block].min(axis=0) for a in cuts])
    up, down = np.maximum(queries, 0), np.minimum(queries, 0)
    bounds = up @ top.T + down @ low.T
    order = np.argsort(-bounds, axis=1, kind="stable") if not big else np.array([sorted(range(len(cuts)), key=lambda j, r=r: -bounds[r, j]) for r in range(len(queries))])
    n = len(queries)
    kth = np.full(n, -np.inf, object if big else np.float64)
    live, scored = np.arange(n), 0
    best_s: list = [np.zeros(0, object if big else np.float64)] * n
    best_id: list = [np.zeros(0, np.int64)] * n
    for step in range(len(cuts)):
        live = live[bounds[live, order[live, step]] >= kth[live]]
        if not len(live):
            break
        blocks = order[live, step]
        for j in np.unique(blocks).tolist():
            own = live[blocks == j]
            a = cuts[j]
            part, part_ids = rows[a : a + block], ids[a : a + block]
            scores = queries[own] @ part.T
            scored += len(own)
            for r, q in enumerate(own.tolist()):
                s = scores[r]
                fit = np.flatnonzero((s >= kth[q]) & (part_ids != qid[q]))
                if not len(fit):
                    continue
                cs, ci = np.concatenate([best_s[q], s[fit]]), np.concatenate([best_id[q], part_ids[fit]])
                first = np.lexsort((ci, -cs))[:k] if not big else np.array(sorted(range(len(cs)), key=lambda i: (-cs[i], ci[i]))[:k])
                best_s[q], best_id[q] = cs[first], ci[first]
                if len(first) == k:
                    kth[q] = best_s[q][-1]
    return np.repeat(np.arange(n), [len(x) for x in best_id]), np.concatenate(best_id), np.concatenate(best_s), scored


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 5, scale: int = 256, block: int = 256, cell_rows: int = 1 << 15, cell_queries: int = 2048, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """query_id, rank (from 1), vec_id, score of the k best rows for each query, ties to the smaller vec_id.

    vectors and queries have an id and a vector; a query's own id is no candidate. Rows whose id is null, or whose
    vector is null or holds a null or non-finite component, take no part; vectors of differing length compare as
    if the shorter ended in zeros. Ids are taken as keys: a repeated row may fill several ranks, a repeated query
    counts once. Fewer than k candidates give fewer rows; empty tables none; further columns are ignored.
    The work is a grid of cells, each one group of queries against one group of blocks, so neither side need fit
    one machine; both sides are dealt by cell.
    """
    v, q = quantise(vectors, scale, id_col, vec_col), quantise(queries, scale, id_col, vec_col).dropDuplicates(["vec_id"])
    (n, w), (nq, wq) = (x.agg(F.count("*"), F.max(F.size("v"))).first() for x in (v, q))
    width = max(w or 0, wq or 0, 1)
    c, g = max(1, -(-n // cell_rows)), max(1, -(-nq // cell_queries))
    least = int(vectors.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    c = max(c, min(-(-least // g), -(-n // (4 * block)) or 1))
    home = F.pmod(F.xxhash64(F.floor(F.col("vec_id") / block)), F.lit(c)).cast("int")  # neighbouring ids stay in one block, whatever steps ids go in
    left = q.withColumn("g", F.pmod(F.xxhash64("vec_id"), F.lit(g)).cast("int")).withColumn("c", F.explode(F.sequence(F.lit(0), F.lit(c - 1))))
    right = v.withColumn("c", home).withColumn("g", F.explode(F.sequence(F.lit(0), F.lit(g - 1))))

    def cell(a: pa.Table, b: pa.Table) -> pa.Table:
        names = ["query_id", "vec_id", "score"]
        if not a.num_rows or not b.num_rows:
            return pa.table([pa.array([], pa.int64())] * 3, names=names)
        b = b.sort_by("vec_id")
        qid = a.column("vec_id").to_numpy()
        n, ids, s, _ = best_of_blocks(_matrix(a.column("v"), width), qid, _matrix(b.column("v"), width), b.column("vec_id").to_numpy(), block, k)
        return pa.table([pa.array(qid[n]), pa.array(ids), pa.array([int(x) for x in s], pa.int64())], names=names)

    got = left.groupBy("g", "c").cogroup(right.groupBy("g", "c")).applyInArrow(cell, "query_id long, vec_id long, score long")
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return got.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")

"""Run-length encoded vectors: struct<runs array<long>, vals array<double>>.

Operators on one vector work on its runs in expressions; operators on two walk both
run lists in step, in numpy on Arrow batches, at a cost of the runs and not of the
length.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

TYPE = "struct<runs:array<long>,vals:array<double>>"


def encode(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    x = np.asarray(x, np.float64)
    if not len(x):
        return np.zeros(0, np.int64), np.zeros(0)
    same = (x[1:] == x[:-1]) | (np.isnan(x[1:]) & np.isnan(x[:-1]))
    start = np.flatnonzero(np.concatenate([[True], ~same]))
    return np.diff(np.append(start, len(x))), x[start]


def merge_runs(ra, va, rb, vb, op) -> tuple[np.ndarray, np.ndarray]:
    """op on two vectors of one length, run by run; equal neighbours join."""
    ea, eb = np.cumsum(ra), np.cumsum(rb)
    if (ea[-1] if len(ea) else 0) != (eb[-1] if len(eb) else 0):
        raise ValueError("vectors differ in length")
    ends = np.union1d(ea, eb)
    with np.errstate(divide="ignore", invalid="ignore"):
        v = op(np.asarray(va)[np.searchsorted(ea, ends)], np.asarray(vb)[np.searchsorted(eb, ends)])
    size = np.diff(np.concatenate([[0], ends]))
    keep = np.concatenate([[True], v[1:] != v[:-1]]) if len(v) else np.zeros(0, bool)
    at = np.flatnonzero(keep)
    return (np.add.reduceat(size, at) if len(at) else size), v[at]


def from_dense(x: str | Column) -> Column:
    """Runs of a dense array, by one fold over its elements."""
    x = (F.col(x) if isinstance(x, str) else x).cast("array<double>")
    zero = F.struct(F.array().cast("array<long>").alias("runs"), F.array().cast("array<double>").alias("vals"))

    def step(acc, v):
        last = F.try_element_at(acc["vals"], F.lit(-1))
        more = F.coalesce(last == v, F.lit(False))
        n = F.size(acc["runs"])
        return F.struct(
            F.when(more, F.concat(F.slice(acc["runs"], F.lit(1), F.greatest(n - 1, F.lit(0))), F.array(F.try_element_at(acc["runs"], F.lit(-1)) + 1))).otherwise(F.concat(acc["runs"], F.array(F.lit(1).cast("long")))).alias("runs"),
            F.when(more, acc["vals"]).otherwise(F.concat(acc["vals"], F.array(v))).alias("vals"),
        )

    return F.aggregate(x, zero, step)


def to_dense(s: str | Column) -> Column:
    s = F.col(s) if isinstance(s, str) else s
    return F.flatten(F.zip_with(s["runs"], s["vals"], lambda r, v: F.array_repeat(v, r.cast("int"))))


def from_pairs(idx: str, val: str, length: int) -> Column:
    """From positions (from 0, rising) and values; all else is 0."""
    dense = F.transform(F.sequence(F.lit(0), F.lit(length - 1)), lambda i: F.coalesce(F.get(F.col(val), (F.array_position(F.col(idx), i) - 1).cast("int")), F.lit(0.0)))
    return from_dense(dense)


def length(s) -> Column:
    s = F.col(s) if isinstance(s, str) else s
    return F.aggregate(s["runs"], F.lit(0).cast("long"), lambda a, r: a + r)


def _weighted(s, f) -> Column:
    s = F.col(s) if isinstance(s, str) else s
    return F.aggregate(F.zip_with(s["runs"], s["vals"], lambda r, v: r * f(v)), F.lit(0.0), lambda a, b: a + b)


def norm1(s) -> Column:
    return _weighted(s, F.abs)


def norm2(s) -> Column:
    return F.sqrt(_weighted(s, lambda v: v * v))


def apply(s, f) -> Column:
    """f on every value, run by run: scale, log, exp and the like."""
    s = F.col(s) if isinstance(s, str) else s
    return F.struct(s["runs"].alias("runs"), F.transform(s["vals"], f).alias("vals"))


def lookup(s, i: int) -> Column:
    """Element i, from 0; null beyond the end."""
    s = F.col(s) if isinstance(s, str) else s
    ends = F.transform(s["runs"], lambda r, k: F.aggregate(F.slice(s["runs"], F.lit(1), k + 1), F.lit(0).cast("long"), lambda a, b: a + b))
    return F.get(s["vals"], F.size(F.filter(ends, lambda e: e <= i)))


def concat(a, b) -> Column:
    a, b = (F.col(x) if isinstance(x, str) else x for x in (a, b))
    return F.struct(F.concat(a["runs"], b["runs"]).alias("runs"), F.concat(a["vals"], b["vals"]).alias("vals"))


def slice_(s, start: int, n: int) -> Column:
    return from_dense(F.slice(to_dense(s), start + 1, n))


OPS = {"add": np.add, "sub": np.subtract, "mult": np.multiply, "div": np.divide}


def binary(df: DataFrame, a: str, b: str, op: str, out: str) -> DataFrame:
    """df with out = a op b on runs; a null on either side gives null."""
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema)
    ia, ib = df.columns.index(a), df.columns.index(b)
    kind = pa.struct([("runs", pa.list_(pa.int64())), ("vals", pa.list_(pa.float64()))])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in batches:
            rows = []
            for x, y in zip(t.column(ia).to_pylist(), t.column(ib).to_pylist()):
                if x is None or y is None:
                    rows.append(None)
                else:
                    r, v = merge_runs(x["runs"], x["vals"], y["runs"], y["vals"], OPS[op])
                    rows.append({"runs": r.tolist(), "vals": v.tolist()})
            yield pa.RecordBatch.from_arrays([*t.columns, pa.array(rows, kind)], names=[*t.schema.names, out])

    return df.mapInArrow(work, f"{fields}, `{out}` {TYPE}")


def dot(df: DataFrame, a: str, b: str, out: str) -> DataFrame:
    return binary(df, a, b, "mult", "__p").withColumn(out, _weighted("__p", lambda v: v)).drop("__p")


def distance(df: DataFrame, a: str, b: str, out: str) -> DataFrame:
    return binary(df, a, b, "sub", "__p").withColumn(out, norm2("__p")).drop("__p")


def equal(a, b) -> Column:
    """Same elements; runs are maximal, so equal vectors have equal runs."""
    a, b = (F.col(x) if isinstance(x, str) else x for x in (a, b))
    return (a["runs"] == b["runs"]) & (a["vals"] == b["vals"])


def sum_vectors(df: DataFrame, col: str, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, pos, sum, n_nonzero) of the stored runs' nonzero elements; zeros cost nothing."""
    s = F.col(col)
    start = F.transform(s["runs"], lambda r, k: F.aggregate(F.slice(s["runs"], F.lit(1), k), F.lit(0).cast("long"), lambda a, b: a + b))
    runs = F.filter(F.arrays_zip(start.alias("s"), s["runs"].alias("r"), s["vals"].alias("v")), lambda z: z["v"] != 0)
    each = df.select(*by, F.explode(runs).alias("z")).select(*by, F.explode(F.sequence(F.col("z.s"), F.col("z.s") + F.col("z.r") - 1)).alias("pos"), F.col("z.v").alias("v"))
    return each.groupBy(*by, "pos").agg(F.sum("v").alias("sum"), F.count("*").alias("n_nonzero"))


def tf_idf(terms: DataFrame, docs: int | None = None) -> DataFrame:
    """(doc_id, term, tf_idf) from (doc_id, term, cnt): cnt * ln(N / df)."""
    n = terms.select("doc_id").distinct().count() if docs is None else docs
    df = terms.groupBy("term").agg(F.countDistinct("doc_id").alias("df"))
    return terms.join(df, "term").select("doc_id", "term", (F.col("cnt") * F.log(F.lit(float(n)) / F.col("df"))).alias("tf_idf"))

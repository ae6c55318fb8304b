"""Ordinary least squares in one pass: sums of products per partition, merged in a tree, solved on one task.

Kernels differ in how a partition forms its sums and agree in the numbers:
blas (block products, lower triangle kept), rowvec (full outer product of each row),
loop (scalar loops), expr (generated SQL sums, groupable at any scale), block
(triangle merged in pieces, for wide rows), jvm (the engine's own Gramian).
"""

from __future__ import annotations

import math
from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rowfold.core import validate
from rowfold.core.bridge import matrix, packed, unpacked, vector
from rowfold.core.fold import Fold, _arrow_schema, run_fold
from rowfold.functions.dist import t_two_sided

RESULT = (
    "coef array<double>, r2 double, std_err array<double>, t_stats array<double>, p_values array<double>, "
    "condition_no double, n long, d int, rank int, sse double, sigma2 double"
)


def solve(n: float, sy: float, syy: float, xy: np.ndarray, gram: np.ndarray, rows: int, cut: float = 8.0) -> dict:
    """The composite result from the sums. Eigenvalues below cut * d * eps of the largest are left out, which gives
    the least-norm coefficients of a rank-deficient table. condition_no is that of X'X."""
    d = len(xy)
    lam, q = np.linalg.eigh(gram)
    top = lam[-1] if d else 0.0
    kept = lam > max(top, 0.0) * d * np.finfo(float).eps * cut
    inv = np.where(kept, 1 / np.where(kept, lam, 1.0), 0.0)
    pinv = (q * inv) @ q.T
    coef = pinv @ xy
    rank = int(kept.sum())
    sse = max(0.0, float(syy - 2 * coef @ xy + coef @ gram @ coef))
    tss = float(syy - sy * sy / n) if n else 0.0
    dof = rows - rank
    sigma2 = sse / dof if dof > 0 else math.nan
    err = np.sqrt(np.maximum(np.diag(pinv), 0.0) * sigma2)
    with np.errstate(divide="ignore", invalid="ignore"):
        t = np.where(err > 0, coef / np.where(err > 0, err, 1.0), np.inf * np.sign(coef))
    p = [t_two_sided(float(v), dof) if dof > 0 else math.nan for v in t]
    low = lam[kept][0] if rank == d and rank else 0.0
    return {
        "coef": coef.tolist(), "r2": 1 - sse / tss if tss > 0 else math.nan, "std_err": err.tolist(), "t_stats": t.tolist(), "p_values": p,
        "condition_no": float(top / low) if low > 0 else math.inf, "n": int(rows), "d": d, "rank": rank, "sse": sse, "sigma2": sigma2,
    }


class OlsFold(Fold):
    """State: rows, sum of weights, sums of y and y^2, X'y, lower triangle of X'X."""

    schema = RESULT

    def __init__(self, kernel: str = "blas", weighted: bool = False):
        self.kernel, self.weighted = kernel, weighted

    def zero(self):
        return None

    def step(self, state, batch: pa.RecordBatch):
        x, y = matrix(batch.column(0)), vector(batch.column(1))
        w = vector(batch.column(2)) if self.weighted else np.ones(len(y))
        if not (np.isfinite(x).all() and np.isfinite(y).all() and np.isfinite(w).all()):
            raise ValueError(f"{int((~np.isfinite(x)).any(axis=1).sum() + (~np.isfinite(y)).sum())} rows hold a number that is not finite")
        d = x.shape[1]
        if self.kernel == "loop":
            g, xy = np.zeros((d, d)), np.zeros(d)
            for r in range(len(y)):
                row = x[r].tolist()
                for i in range(d):
                    xy[i] += w[r] * row[i] * y[r]
                    for j in range(d):
                        g[i, j] += w[r] * row[i] * row[j]
        elif self.kernel == "rowvec":
            g, xy = np.zeros((d, d)), np.zeros(d)
            for r in range(len(y)):
                row = np.array(x[r].tolist())
                g += np.outer(row, row * w[r])
                xy += row * (w[r] * y[r])
        else:
            xw = x * w[:, None] if self.weighted else x
            g, xy = x.T @ xw, xw.T @ y
        own = (len(y), float(w.sum()), float(w @ y), float((w * y) @ y), xy, packed(g))
        return own if state is None else self.merge(state, own)

    def merge(self, a, b):
        if a is None or b is None:
            return b if a is None else a
        if len(a[4]) != len(b[4]):
            raise ValueError("vectors differ in length")
        return tuple(p + q for p, q in zip(a, b))

    def finish(self, state):
        if state is None:
            return []
        rows, n, sy, syy, xy, tri = state
        return [solve(n, sy, syy, xy, unpacked(tri, len(xy)), rows)]


def sums(d: int, xs: Sequence[Column], y: Column, w: Column | None = None) -> list[Column]:
    """The sums as generated expressions: n, y, y^2, X'y and the lower triangle of X'X, by name."""
    v = w if w is not None else F.lit(1.0)
    out = [F.count("*").alias("rows"), F.sum(v).alias("n"), F.sum(v * y).alias("sy"), F.sum(v * y * y).alias("syy")]
    out += [F.sum(v * xs[i] * y).alias(f"xy{i}") for i in range(d)]
    return out + [F.sum(v * xs[i] * xs[j]).alias(f"g{i}_{j}") for i in range(d) for j in range(i + 1)]


def _expr(df: DataFrame, y: str, x: str, by: Sequence[str], w: str | None, d: int | None) -> DataFrame:
    d = d or validate.same_length(df, x)
    if d > 64:
        raise validate.InputError("TOO_WIDE", f"{d} variables give {d * (d + 3) // 2} sums", "use the blas or block kernel")
    xs = [F.get(F.col(x), F.lit(i)).cast("double") for i in range(d)]
    agg = df.groupBy(*by).agg(*sums(d, xs, F.col(y).cast("double"), F.col(w).cast("double") if w else None)).filter("rows > 0")

    def finish(batches):
        for b in batches:
            t = b.to_pydict()
            k = len(by)
            names = b.schema.names
            rows = []
            for i in range(b.num_rows):
                r = {n: t[n][i] for n in names}
                tri = np.array([r[f"g{a}_{c}"] for a in range(d) for c in range(a + 1)])
                rows.append(solve(r["n"], r["sy"], r["syy"], np.array([r[f"xy{a}"] for a in range(d)]), unpacked(tri, d), r["rows"]))
            kinds = {"coef": pa.list_(pa.float64()), "std_err": pa.list_(pa.float64()), "t_stats": pa.list_(pa.float64()), "p_values": pa.list_(pa.float64()), "n": pa.int64(), "d": pa.int32(), "rank": pa.int32()}
            cols = [pa.array([r[c] for r in rows], kinds.get(c, pa.float64())) for c in (f.split()[0] for f in RESULT.split(", "))]
            yield pa.RecordBatch.from_arrays([*b.columns[:k], *cols], names=[*names[:k], *(f.split()[0] for f in RESULT.split(", "))])

    keys = "".join(f"`{n}` {dict(df.dtypes)[n]}, " for n in by)
    return agg.mapInArrow(finish, keys + RESULT)


def _block(df: DataFrame, y: str, x: str, block: int) -> DataFrame:
    """Partial states in square blocks of the lower triangle, so that merging is itself spread over tasks."""

    def partial(batches):
        fold, state = OlsFold(), None
        for b in batches:
            if b.num_rows:
                state = fold.step(state, b)
        if state is None:
            return
        rows, n, sy, syy, xy, tri = state
        g = unpacked(tri, len(xy))
        d = len(xy)
        keys, data = [(-1, -1)], [np.array([rows, n, sy, syy, *xy]).tobytes()]
        for i in range(0, d, block):
            for j in range(0, i + 1, block):
                keys.append((i, j))
                data.append(g[i : i + block, j : j + block].tobytes())
        yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in keys], pa.int32()), pa.array([k[1] for k in keys], pa.int32()), pa.array(data, pa.binary())], names=["bi", "bj", "data"])

    def add(key, t):
        total = sum(np.frombuffer(v, np.float64) for v in t.column("data").to_pylist())
        return pa.table([pa.array([key[0].as_py()], pa.int32()), pa.array([key[1].as_py()], pa.int32()), pa.array([total.tobytes()], pa.binary())], names=["bi", "bj", "data"])

    def finish(t):
        parts = {(a, b): np.frombuffer(v, np.float64) for a, b, v in zip(*(t.column(c).to_pylist() for c in ("bi", "bj", "data")))}
        head = parts.pop((-1, -1))
        d = len(head) - 4
        g = np.zeros((d, d))
        for (i, j), v in parts.items():
            h, w = min(block, d - i), min(block, d - j)
            g[i : i + h, j : j + w] = v.reshape(h, w)
            g[j : j + w, i : i + h] = v.reshape(h, w).T
        return pa.Table.from_pylist([solve(head[1], head[2], head[3], head[4:], g, int(head[0]))], schema=target)

    target = _arrow_schema(df, RESULT)
    level = df.select(x, y).mapInArrow(partial, "bi int, bj int, data binary").groupBy("bi", "bj").applyInArrow(add, "bi int, bj int, data binary")
    return level.withColumn("one", F.lit(0)).groupBy("one").applyInArrow(lambda t: finish(t.drop_columns("one")), RESULT)


def _jvm(df: DataFrame, y: str, x: str) -> DataFrame:
    """The engine's own Gramian of (x, y) rows, as a reference."""
    from pyspark.mllib.linalg import Vectors
    from pyspark.mllib.linalg.distributed import RowMatrix

    rows = df.select(x, F.col(y).cast("double").alias("y")).rdd.map(lambda r: Vectors.dense([*r[0], r[1], 1.0]))
    m = RowMatrix(rows)
    g = m.computeGramianMatrix().toArray()
    d = len(g) - 2
    r = solve(g[-1, -1], g[-1, d], g[d, d], g[:d, d], g[:d, :d], int(g[-1, -1]))
    return df.sparkSession.createDataFrame([tuple(r.values())], RESULT)


def ols(df: DataFrame, y: str, x: str, by: Sequence[str] = (), kernel: str = "blas", weights: str | None = None, mode: str | None = None, d: int | None = None, block: int = 64) -> DataFrame:
    """Least squares of y on the vector x. Rows with a null in y, x or the weights are left out."""
    validate.vector(df, x)
    validate.numeric(df, y)
    used = [x, y, *([weights] if weights else [])]
    src = df.select(*by, *used).dropna(subset=used).filter(~F.exists(x, lambda c: c.isNull()))
    src = src.withColumn(x, F.col(x).cast("array<double>")).withColumn(y, F.col(y).cast("double"))
    if kernel == "expr":
        return _expr(src, y, x, by, weights, d)
    if kernel == "block":
        return _block(src, y, x, block)
    if kernel == "jvm":
        return _jvm(src, y, x)
    if kernel not in ("blas", "rowvec", "loop"):
        raise validate.InputError("UNKNOWN_KERNEL", f"no kernel {kernel!r}", "blas, rowvec, loop, expr, block or jvm")
    return run_fold(src, OlsFold(kernel, weights is not None), used, by, mode or ("partial" if by else "tree"))


class SparseOlsFold(OlsFold):
    """The same over (index, value) vectors of d components: only pairs of stored components are multiplied."""

    def __init__(self, d: int):
        super().__init__()
        self.d = d

    def step(self, state, batch: pa.RecordBatch):
        idx, val, y = batch.column(0), batch.column(1), vector(batch.column(2))
        off = np.asarray(idx.offsets) - idx.offsets[0].as_py()
        i, v = np.asarray(idx.flatten(), dtype=np.int64), np.asarray(val.flatten(), dtype=np.float64)
        g, xy = np.zeros((self.d, self.d)), np.zeros(self.d)
        np.add.at(xy, i, v * np.repeat(y, np.diff(off)))
        for a, z in zip(off[:-1], off[1:]):
            g[np.ix_(i[a:z], i[a:z])] += np.outer(v[a:z], v[a:z])
        own = (len(y), float(len(y)), float(y.sum()), float(y @ y), xy, packed(g))
        return own if state is None else self.merge(state, own)


def ols_sparse(df: DataFrame, y: str, idx: str, val: str, d: int) -> DataFrame:
    src = df.select(F.col(idx).cast("array<long>").alias(idx), F.col(val).cast("array<double>").alias(val), F.col(y).cast("double").alias(y)).dropna()
    return run_fold(src, SparseOlsFold(d), [idx, val, y])


def simple_ols(df: DataFrame, y: str, x: str, by: Sequence[str] = ()) -> DataFrame:
    """Slope, intercept and R^2 of y on one x, by the engine's own aggregates."""
    a, b = F.col(y).cast("double"), F.col(x).cast("double")
    return df.groupBy(*by).agg(F.regr_slope(a, b).alias("slope"), F.regr_intercept(a, b).alias("intercept"), F.regr_r2(a, b).alias("r2"), F.regr_count(a, b).alias("n"))


def predict_ols(df: DataFrame, x: str, coef: Sequence[float]) -> Column:
    return F.aggregate(F.zip_with(F.col(x).cast("array<double>"), F.array(*map(F.lit, map(float, coef))), lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)

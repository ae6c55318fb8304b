"""Objectives that are sums over rows, and solvers that need nothing else of them.

A row is one term. An objective gives a batch's loss and gradient at w, a step of
its incremental chain and, for penalties without a gradient, a proximal map; any
solver then fits any objective: batch gradient descent, one incremental chain,
chains per partition whose models are averaged, or mini-batches.
"""

from __future__ import annotations

import math
import pickle
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowfold.core import validate
from rowfold.core.bridge import matrix, vector
from rowfold.core.driver import FitResult, IterationLog, relative_change
from rowfold.core.fold import Fold, run_fold


class Step:
    """Step sizes by round."""

    @staticmethod
    def inv(a: float = 1.0) -> Callable[[int], float]:
        return lambda k: a / k

    @staticmethod
    def const(a: float) -> Callable[[int], float]:
        return lambda k: a

    @staticmethod
    def decay(a: float, lam: float) -> Callable[[int], float]:
        return lambda k: a / (1 + lam * k)

    @staticmethod
    def geometric(a: float, g: float) -> Callable[[int], float]:
        return lambda k: a * g**k


class Objective:
    """Sum of terms over rows of columns (x, y). Penalties are per row, so that they weigh like the mean loss."""

    columns = ("x", "y")

    def __init__(self, d: int):
        self.d = d

    def start(self) -> np.ndarray:
        return np.zeros(self.d)

    def read(self, batch: pa.RecordBatch):
        return matrix(batch.column(0)), vector(batch.column(1))

    def loss(self, w, data) -> float:
        raise NotImplementedError

    def grad(self, w, data) -> np.ndarray:
        raise NotImplementedError

    def rows(self, data) -> int:
        return len(data[1])

    def take(self, data, i):
        return tuple(v[i : i + 1] for v in data)

    def prox(self, w, step: float) -> np.ndarray:
        return w

    def penalty(self, w) -> float:
        return 0.0


class LeastSquares(Objective):
    def loss(self, w, data):
        r = data[0] @ w - data[1]
        return float(r @ r)

    def grad(self, w, data):
        return 2 * data[0].T @ (data[0] @ w - data[1])


class Lasso(LeastSquares):
    """Squared error and mu times the sum of absolute coefficients; prox by soft threshold, or its subgradient."""

    def __init__(self, d: int, mu: float, subgradient: bool = False):
        super().__init__(d)
        self.mu, self.subgradient = mu, subgradient

    def penalty(self, w):
        return self.mu * float(np.abs(w).sum())

    def grad(self, w, data):
        g = super().grad(w, data)
        return g + self.mu * np.sign(w) * len(data[1]) if self.subgradient else g

    def prox(self, w, step):
        return w if self.subgradient else np.sign(w) * np.maximum(np.abs(w) - step * self.mu, 0)


class Logistic(Objective):
    """Labels 0 and 1 (taken as -1 and 1)."""

    def __init__(self, d: int, l2: float = 0.0):
        super().__init__(d)
        self.l2 = l2

    def loss(self, w, data):
        m = (2 * data[1] - 1) * (data[0] @ w)
        return float((np.maximum(-m, 0) + np.log1p(np.exp(-np.abs(m)))).sum())

    def grad(self, w, data):
        s = 2 * data[1] - 1
        m = s * (data[0] @ w)
        p = np.where(m >= 0, np.exp(-np.abs(m)), 1.0) / (1 + np.exp(-np.abs(m)))
        return -data[0].T @ (s * p) + self.l2 * w * len(s)

    def penalty(self, w):
        return self.l2 / 2 * float(w @ w)


class LinearSvm(Objective):
    """Hinge loss on labels 0 and 1 (as -1 and 1), with l2/2 times the squared norm."""

    def __init__(self, d: int, l2: float = 0.01):
        super().__init__(d)
        self.l2 = l2

    def loss(self, w, data):
        return float(np.maximum(0, 1 - (2 * data[1] - 1) * (data[0] @ w)).sum())

    def grad(self, w, data):
        s = 2 * data[1] - 1
        short = s * (data[0] @ w) < 1
        return -data[0].T @ (s * short) + self.l2 * w * len(s)

    def penalty(self, w):
        return self.l2 / 2 * float(w @ w)


class InsensitiveRegression(Objective):
    """Absolute error beyond eps."""

    def __init__(self, d: int, eps: float = 0.1, l2: float = 0.01):
        super().__init__(d)
        self.eps, self.l2 = eps, l2

    def loss(self, w, data):
        return float(np.maximum(0, np.abs(data[0] @ w - data[1]) - self.eps).sum())

    def grad(self, w, data):
        r = data[0] @ w - data[1]
        return data[0].T @ (np.sign(r) * (np.abs(r) > self.eps)) + self.l2 * w * len(r)

    def penalty(self, w):
        return self.l2 / 2 * float(w @ w)


class Novelty(Objective):
    """One class: w = (weights, rho); points whose score falls below rho pay 1/nu."""

    def __init__(self, d: int, nu: float = 0.1):
        super().__init__(d + 1)
        self.nu = nu

    def loss(self, w, data):
        return float((np.maximum(0, w[-1] - data[0] @ w[:-1]) / self.nu - w[-1]).sum())

    def grad(self, w, data):
        out = data[0] @ w[:-1] < w[-1]
        n = len(data[0])
        return np.append(-data[0].T @ out / self.nu + w[:-1] * n, out.sum() / self.nu - n)

    def penalty(self, w):
        return float(w[:-1] @ w[:-1]) / 2


class _LossFold(Fold):
    """Rows, loss and gradient at w in one pass."""

    schema = "n long, loss double, grad array<double>"

    def __init__(self, obj: Objective, w: np.ndarray):
        self.obj, self.w = obj, w

    def zero(self):
        return (0, 0.0, np.zeros_like(self.w))

    def step(self, s, batch):
        data = self.obj.read(batch)
        return self.merge(s, (self.obj.rows(data), self.obj.loss(self.w, data), self.obj.grad(self.w, data)))

    def merge(self, a, b):
        return tuple(p + q for p, q in zip(a, b))

    def finish(self, s):
        return [{"n": s[0], "loss": s[1], "grad": s[2].tolist()}]


class _ChainFold(Fold):
    """A chain of single-row (or mini-batch) steps through a partition's rows; chains merge by averaging, weighted by rows."""

    schema = "n long, w array<double>, loss double"

    def __init__(self, obj: Objective, w: np.ndarray, step: float, size: int, average: bool):
        self.obj, self.w, self.alpha, self.size, self.average = obj, w, step, size, average

    def zero(self):
        return None

    def step(self, s, batch):
        data = self.obj.read(batch)
        n, w, loss = s or (0, self.w.copy(), 0.0)
        rows = self.obj.rows(data)
        for i in range(0, rows, self.size):
            own = tuple(v[i : i + self.size] for v in data)
            k = min(self.size, rows - i)
            loss += self.obj.loss(w, own)
            w = self.obj.prox(w - self.alpha * self.obj.grad(w, own) / k, self.alpha)
        return (n + rows, w, loss)

    def merge(self, a, b):
        if a is None or b is None:
            return b if a is None else a
        return (a[0] + b[0], (a[0] * a[1] + b[0] * b[1]) / (a[0] + b[0]), a[2] + b[2])

    def finish(self, s):
        return [] if s is None else [{"n": s[0], "w": s[1].tolist(), "loss": s[2]}]


def fit(
    obj: Objective, df: DataFrame, solver: str = "igd", mode: str = "average", stepsize: Callable[[int], float] | None = None, max_iter: int = 20, tol: float = 1e-6,
    batch: int = 1, shuffle: str = "once", seed: int = 0, scale_by_n: bool = False, start: np.ndarray | None = None,
) -> FitResult:
    """Minimise the objective over rows of df. solver gd: full gradient of the mean loss per round, with halving of steps
    that raise the loss when stepsize is None; igd: incremental steps, mode serial (one chain) or average (one a
    partition); minibatch: igd with batch rows a step. scale_by_n multiplies gradients by the number of rows, as a sum over
    terms has it; the step must then hold 1/n."""
    for c in obj.columns:
        validate.columns(df, c)
    src = df.select(*obj.columns)
    chains = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))  # by number, so that a cached and a new order have as many

    def dealt(rows: DataFrame, epoch: int) -> DataFrame:
        """The rows in an order of their hashes that differs from epoch to epoch, dealt anew over the partitions."""
        rows = rows.withColumn("__o", F.xxhash64(F.lit(seed), F.lit(epoch), *obj.columns))
        return rows.repartition(chains, "__o").sortWithinPartitions("__o").drop("__o") if mode != "serial" else rows.coalesce(1).sortWithinPartitions("__o").drop("__o")

    if shuffle not in ("once", "epoch", "none"):
        raise validate.InputError("UNKNOWN_SHUFFLE", f"no order {shuffle!r}", "once, epoch or none")
    if solver != "gd" and shuffle == "once":
        src = dealt(src, 0)
    src = src.persist()
    w = obj.start() if start is None else np.array(start, float)
    log = IterationLog()
    stop = relative_change("loss", tol)
    converged, i = False, 0
    if solver == "gd":

        def at(w: np.ndarray) -> tuple[float, np.ndarray, int]:
            r = run_fold(src, _LossFold(obj, w), obj.columns).first()
            return r["loss"] / r["n"] + obj.penalty(w), np.array(r["grad"]) / r["n"], r["n"]

        now, grad, n = at(w)
        auto = 1.0
        for i in range(1, max_iter + 1):
            a = stepsize(i) * (n if scale_by_n else 1) if stepsize else auto
            new = obj.prox(w - a * grad, a)
            value, g, _ = at(new)
            while stepsize is None and value > now and a > 1e-12:
                a /= 2
                new = obj.prox(w - a * grad, a)
                value, g, _ = at(new)
            auto = a * 1.5
            w, now, grad = new, value, g
            log.append(i, loss=now, step=a)
            if stop(log):
                converged = True
                break
    else:
        size = batch if solver == "minibatch" else 1
        steps = stepsize or Step.decay(0.1, 0.5)
        for i in range(1, max_iter + 1):
            own = dealt(src, i) if shuffle == "epoch" else src
            r = run_fold(own, _ChainFold(obj, w, steps(i), size, mode == "average"), obj.columns, mode="serial" if mode == "serial" else "tree").first()
            w = np.array(r["w"])
            log.append(i, loss=r["loss"] / r["n"] + obj.penalty(w), step=steps(i))
            if stop(log):
                converged = True
                break
    src.unpersist()
    frame = df.sparkSession.createDataFrame([(j, float(v)) for j, v in enumerate(w)], "pos int, value double")
    return FitResult(w, log, i, converged, frame)


def minimise_scalar(f_grad: Callable[[float], float], x: float, stepsize: Callable[[int], float], rounds: int) -> list[float]:
    """Gradient descent on a function of one number: the path."""
    path = [x]
    for k in range(1, rounds + 1):
        path.append(path[-1] - stepsize(k) * f_grad(path[-1]))
    return path


def low_rank(df: DataFrame, i: str, j: str, v: str, rank: int, mu: float = 0.05, epochs: int = 10, step: float = 0.05, blocks: int | None = None, seed: int = 0, block_cells: int = 500_000) -> FitResult:
    """Factors of a table of observed cells by incremental steps. Rows and columns fall into blocks x blocks strata (so
    many that a stratum has about block_cells cells, at least 4 x 4); the
    strata of a diagonal share no factor row, so each diagonal is one parallel sub-epoch. Not convex: descent is all
    that can be expected. The factors stay tables (side, key, block, f)."""
    from rowfold.core.driver import stage

    cells = df.select(F.col(i).cast("string").alias("i"), F.col(j).cast("string").alias("j"), F.col(v).cast("double").alias("v")).dropna()
    blocks = blocks or max(4, math.ceil(math.sqrt(cells.count() / block_cells)))
    cells = stage(cells.withColumn("bi", F.pmod(F.xxhash64("i"), F.lit(blocks)).cast("int")).withColumn("bj", F.pmod(F.xxhash64("j"), F.lit(blocks)).cast("int")), "cells")
    first = lambda c: F.transform(F.sequence(F.lit(1), F.lit(rank)), lambda k: (F.pmod(F.xxhash64(F.lit(seed), F.lit(c), "key", k), F.lit(1000)) / 1000.0 - 0.5) * 0.2 + 0.1)
    L = cells.groupBy(F.col("i").alias("key"), F.col("bi").alias("b")).agg(F.count("*").alias("n")).withColumn("f", first("i"))
    R = cells.groupBy(F.col("j").alias("key"), F.col("bj").alias("b")).agg(F.count("*").alias("n")).withColumn("f", first("j"))
    L, R = stage(L, "L"), stage(R, "R")
    log = IterationLog()
    n = cells.count()
    out_schema = "side string, key string, b int, n long, f array<double>, loss double"

    def sub_epoch(d: int, alpha: float):
        def work(_, left: pa.Table, right: pa.Table) -> pa.Table:
            f = {"L": {}, "R": {}}
            meta = {"L": {}, "R": {}}
            for r in right.to_pylist():
                f[r["side"]][r["key"]] = np.array(r["f"])
                meta[r["side"]][r["key"]] = (r["b"], r["n"])
            loss = 0.0
            rng = np.random.default_rng(d)
            rows = left.to_pylist()
            for t in rng.permutation(len(rows)):
                r = rows[t]
                a, b = f["L"][r["i"]], f["R"][r["j"]]
                e = a @ b - r["v"]
                loss += e * e
                ga, gb = 2 * e * b + 2 * mu * a / meta["L"][r["i"]][1], 2 * e * a + 2 * mu * b / meta["R"][r["j"]][1]
                f["L"][r["i"]], f["R"][r["j"]] = a - alpha * ga, b - alpha * gb
            out = [{"side": s, "key": k, "b": meta[s][k][0], "n": meta[s][k][1], "f": v.tolist(), "loss": 0.0} for s in "LR" for k, v in f[s].items()]
            if out:
                out[0]["loss"] = loss
            return pa.Table.from_pylist(out, schema=pa.schema([("side", pa.string()), ("key", pa.string()), ("b", pa.int32()), ("n", pa.int64()), ("f", pa.list_(pa.float64())), ("loss", pa.float64())]))

        return work

    for e in range(1, epochs + 1):
        total = 0.0
        for d in range(blocks):
            own = cells.filter(F.pmod(F.col("bi") - F.col("bj"), F.lit(blocks)) == d).withColumn("s", F.col("bi"))
            model = L.withColumn("side", F.lit("L")).withColumn("s", F.col("b")).unionByName(R.withColumn("side", F.lit("R")).withColumn("s", F.pmod(F.col("b") + d, F.lit(blocks))))
            both = stage(own.groupBy("s").cogroup(model.groupBy("s")).applyInArrow(sub_epoch(d, step / (1 + 0.2 * (e - 1))), out_schema), "factors")
            total += both.agg(F.sum("loss")).first()[0] or 0.0
            L, R = (both.filter(F.col("side") == s).select("key", "b", "n", "f") for s in "LR")
        log.append(e, loss=total / max(1, n))
    frame = L.withColumn("side", F.lit("row")).unionByName(R.withColumn("side", F.lit("column"))).select("side", "key", "f")
    return FitResult(None, log, epochs, True, frame)

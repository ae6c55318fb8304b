"""Binary logistic regression: Newton rounds (iteratively reweighted least squares) and other solvers.

Each round is one fold over the rows with the current coefficients in its closure;
only sums of the size of the model come back.
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
from rowfold.core.driver import FitResult, IterationLog, iterate, stage
from rowfold.core.fold import Fold, run_fold
from rowfold.functions.dist import norm_two_sided

STATE = "n long, loglik double, grad array<double>, hess array<double>, top double"
REPORT = (
    "coef array<double>, log_likelihood double, std_err array<double>, z_stats array<double>, p_values array<double>, "
    "odds_ratios array<double>, condition_no double, iterations int, converged boolean, status string, n long"
)


def sigmoid(eta: np.ndarray) -> np.ndarray:
    e = np.exp(-np.abs(eta))
    return np.where(eta >= 0, 1 / (1 + e), e / (1 + e))


def log1pexp(eta: np.ndarray) -> np.ndarray:
    return np.maximum(eta, 0) + np.log1p(np.exp(-np.abs(eta)))


class LogisticFold(Fold):
    """Log-likelihood, gradient and information at b, and the largest linear term."""

    schema = STATE

    def __init__(self, b: np.ndarray, hessian: bool = True):
        self.b, self.hessian = np.asarray(b, float), hessian

    def zero(self):
        return None

    def step(self, state, batch: pa.RecordBatch):
        x, y = matrix(batch.column(0)), vector(batch.column(1))
        eta = x @ self.b
        p = sigmoid(eta)
        w = p * (1 - p)
        hess = packed(x.T @ (x * w[:, None])) if self.hessian else np.zeros(0)
        own = (len(y), float((y * eta - log1pexp(eta)).sum()), x.T @ (y - p), hess, float(np.abs(eta).max()))
        return own if state is None else self.merge(state, own)

    def merge(self, a, b):
        if a is None or b is None:
            return b if a is None else a
        return (*(p + q for p, q in zip(a[:4], b[:4])), max(a[4], b[4]))

    def finish(self, state):
        return [] if state is None else [dict(zip(("n", "loglik", "grad", "hess", "top"), (state[0], state[1], state[2].tolist(), state[3].tolist(), state[4])))]


def _pinv(g: np.ndarray) -> tuple[np.ndarray, float]:
    lam, q = np.linalg.eigh(g)
    kept = lam > lam[-1] * len(lam) * np.finfo(float).eps * 8
    return (q * np.where(kept, 1 / np.where(kept, lam, 1), 0)) @ q.T, float(lam[-1] / lam[0]) if kept.all() else math.inf


def _report(b, ll, hess, rounds, converged, status, n) -> dict:
    inv, cond = _pinv(hess)
    err = np.sqrt(np.maximum(np.diag(inv), 0))
    z = np.divide(b, err, out=np.full(len(b), np.inf), where=err > 0)
    return {
        "coef": b.tolist(), "log_likelihood": float(ll), "std_err": err.tolist(), "z_stats": z.tolist(), "p_values": [norm_two_sided(float(v)) for v in z],
        "odds_ratios": np.exp(np.minimum(b, 700)).tolist(), "condition_no": cond, "iterations": rounds, "converged": converged, "status": status, "n": n,
    }


def prepare(df: DataFrame, y: str, x: str, by: Sequence[str] = ()) -> DataFrame:
    validate.vector(df, x)
    validate.numeric(df, y)
    return df.select(*by, F.col(x).cast("array<double>").alias("x"), F.col(y).cast("double").alias("y")).dropna(subset=["x", "y"])


def logistic(df: DataFrame, y: str, x: str, solver: str = "irls", tol: float = 1e-8, max_iter: int = 20, cache: bool = True, separated_at: float = 30.0, stepsize: float = 1.0) -> FitResult:
    """Maximise the likelihood of y in {0, 1}. solver: irls, cg (nonlinear conjugate gradient), gd (batch gradient).

    A fit whose linear terms pass separated_at while the likelihood still rises is reported as separated, not as
    converged: its likelihood has no maximum.
    """
    src = prepare(df, y, x)
    if cache:
        src = src.persist()
    first = src.select(F.size("x").alias("d")).first()
    if first is None:
        raise validate.InputError("EMPTY_INPUT", "no rows to fit")
    d = first["d"]

    def at(b: np.ndarray, hessian: bool = True) -> dict:
        r = run_fold(src, LogisticFold(b, hessian), ["x", "y"]).first()
        return {"n": r["n"], "ll": r["loglik"], "grad": np.array(r["grad"]), "hess": unpacked(np.array(r["hess"]), d) if hessian else None, "top": r["top"]}

    def newton(state, i):
        b, now = state
        step = _pinv(now["hess"])[0] @ now["grad"]
        scale, new = 1.0, at(b + step)
        while new["ll"] < now["ll"] - 1e-9 * abs(now["ll"]) and scale > 1e-4:  # a shorter step where a full one overshoots
            scale /= 2
            new = at(b + scale * step)
        b = b + scale * step
        return (b, new), {"log_likelihood": new["ll"], "change": abs(new["ll"] - now["ll"]), "top": new["top"]}

    def gradient(state, i):
        b, now = state
        step, grad = stepsize, now["grad"] / now["n"]
        new = at(b + step * grad)
        while new["ll"] < now["ll"] + 1e-4 * step * now["n"] * (grad @ grad) and step > 1e-10:
            step /= 2
            new = at(b + step * grad)
        b = b + step * grad
        return (b, new), {"log_likelihood": new["ll"], "change": abs(new["ll"] - now["ll"]), "top": new["top"]}

    memory: dict = {}

    def conjugate(state, i):
        b, now = state
        g = now["grad"]
        p = g if not memory or i % (d + 1) == 0 else g + max(0.0, g @ (g - memory["g"]) / (memory["g"] @ memory["g"])) * memory["p"]
        if p @ g <= 0:
            p = g
        memory.update(g=g, p=p)
        step = float(g @ p / max(p @ now["hess"] @ p, 1e-300))  # along p, the exact step of the local quadratic
        new = at(b + step * p)
        while new["ll"] < now["ll"] and step > 1e-12:
            step /= 2
            new = at(b + step * p)
        b = b + step * p
        return (b, new), {"log_likelihood": new["ll"], "change": abs(new["ll"] - now["ll"]), "top": new["top"]}

    steps = {"irls": newton, "gd": gradient, "cg": conjugate}
    if solver not in steps:
        raise validate.InputError("UNKNOWN_SOLVER", f"no solver {solver!r}", "irls, cg or gd")
    start = np.zeros(d)
    done = lambda log: log.rows[-1]["top"] > separated_at or log.rows[-1]["change"] <= tol * max(1.0, abs(log.rows[-1]["log_likelihood"]))
    fit = iterate((start, at(start)), steps[solver], done, max_iter)
    b, now = fit.state
    separated = now["top"] > separated_at
    fit.converged = fit.converged and not separated
    row = _report(b, now["ll"], now["hess"], fit.iterations, fit.converged, "separated" if separated else "ok" if fit.converged else "max_iter", now["n"])
    fit.state = row
    fit.frame = df.sparkSession.createDataFrame([tuple(row.values())], REPORT)
    if cache:
        src.unpersist()
    return fit


class _GroupedFold(LogisticFold):
    def step(self, state, batch: pa.RecordBatch):
        b = matrix(batch.column(2))
        self.b = b[0]
        return super().step(state, batch)


def logistic_grouped(df: DataFrame, y: str, x: str, by: str, tol: float = 1e-8, max_iter: int = 20, separated_at: float = 30.0) -> DataFrame:
    """One fit per value of `by`. The state is a table of groups and coefficients; groups that have settled are left out
    of later rounds. A group with a single class is flagged (status one_class) and not fitted."""
    src = prepare(df, y, x, [by]).withColumnRenamed(by, "g").persist()
    seen = src.groupBy("g").agg(F.min("y").alias("lo"), F.max("y").alias("hi"), F.max(F.size("x")).alias("d"), F.count("*").alias("n"))
    model = seen.select("g", F.array_repeat(F.lit(0.0), F.col("d")).alias("b"), F.lit(None).cast("double").alias("ll"), F.when(F.col("lo") == F.col("hi"), "one_class").otherwise("open").alias("status"), F.lit(0).alias("rounds"), "n", F.lit(None).cast("array<double>").alias("hess"))
    model = stage(model, "logistic-groups")

    def newton(t: pa.Table) -> pa.Table:
        r = t.to_pylist()[0]
        b, d = np.array(r["b"]), len(r["b"])
        step = _pinv(unpacked(np.array(r["h"]), d))[0] @ np.array(r["grad"])
        ll, before = r["loglik"], r["ll"]
        status = "separated" if r["top"] > separated_at else "ok" if before is not None and abs(ll - before) <= tol * max(1.0, abs(ll)) else "open"
        if status == "open":
            b = b + step
        return pa.table({"g": t.column("g"), "b": pa.array([b.tolist()], pa.list_(pa.float64())), "ll": [ll], "status": [status], "rounds": pa.array([r["rounds"] + 1], pa.int32()), "n": t.column("n"), "hess": pa.array([r["h"]], pa.list_(pa.float64()))})

    kind = dict(df.dtypes)[by]
    for _ in range(max_iter + 1):
        live = model.filter("status = 'open'")
        if live.isEmpty():
            break
        joined = src.join(F.broadcast(live.select("g", "b")), "g")
        sums = run_fold(joined, _GroupedFold(np.zeros(1)), ["x", "y", "b"], ["g"], "partial").withColumnRenamed("hess", "h").drop("n")
        both = live.select("g", "b", "ll", "rounds", "n").join(sums, "g")
        moved = both.groupBy("g").applyInArrow(newton, f"g {kind}, b array<double>, ll double, status string, rounds int, n long, hess array<double>")
        model = stage(moved.unionByName(model.filter("status <> 'open'")), "logistic-groups")
    src.unpersist()
    return model.select(F.col("g").alias(by), F.col("b").alias("coef"), F.col("ll").alias("log_likelihood"), F.when(F.col("status") == "open", "max_iter").otherwise(F.col("status")).alias("status"), (F.col("status") == "ok").alias("converged"), F.col("rounds").alias("iterations"), "n")


def logistic_many(data: DataFrame, specs: dict[int, Sequence[int]], y: str, x: str) -> DataFrame:
    """Many fits in one round loop: each spec names the components of x it uses, and every row is dealt to all specs,
    which are part of the plan."""
    each = F.explode(F.array(*[F.struct(F.lit(int(k)).alias("spec"), F.array(*[F.get(F.col(x), F.lit(int(i))) for i in v]).alias("x")) for k, v in specs.items()]))
    picked = data.select(F.col(y).alias("y"), each.alias("s")).select("y", "s.spec", "s.x")
    return logistic_grouped(picked, "y", "x", "spec")


def predict_logistic(x: str, coef: Sequence[float], kind: str = "prob") -> Column:
    eta = F.aggregate(F.zip_with(F.col(x).cast("array<double>"), F.array(*map(F.lit, map(float, coef))), lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)
    prob = 1 / (1 + F.exp(-eta))
    return (prob >= 0.5).cast("int") if kind == "class" else prob

"""Cost measures of fits: overhead of a job, speed-up by processes, and the cost model of least squares."""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence

import numpy as np
from pyspark.sql import DataFrame


def timed(run: Callable[[], object], repeats: int = 1) -> float:
    """Least wall-clock seconds of some runs."""
    took = []
    for _ in range(repeats):
        t = time.perf_counter()
        run()
        took.append(time.perf_counter() - t)
    return min(took)


def overhead(fit: Callable[[DataFrame], DataFrame], df: DataFrame, repeats: int = 3) -> float:
    """Seconds of a fit over almost no rows: what a job costs before it reads anything."""
    few = df.limit(16).persist()
    few.count()
    s = timed(lambda: fit(few).collect(), repeats)
    few.unpersist()
    return s


def speedup(seconds: dict[int, float]) -> dict[int, dict[str, float]]:
    """By number of processes: how many times faster than the fewest, and the share of the ideal."""
    base = min(seconds)
    return {p: {"speedup": seconds[base] / s, "efficiency": seconds[base] / s * base / p} for p, s in sorted(seconds.items())}


def fit_cost_model(runs: Sequence[tuple[int, int, int, float]], marshalling: bool = False) -> dict[str, float]:
    """seconds = a + b d^3 + c n d^2 / p over runs (n rows, d variables, p processes, seconds), with non-negative
    coefficients, and how much of the variation it explains. marshalling adds a term n d / p: what it costs to hand over a
    row's numbers, which outweighs the products where there are few variables. Runs must differ in rows and in variables."""
    n, d, p, s = (np.array(x, float) for x in zip(*runs))
    names = ["fixed", "cubic", "per_row", *(["per_value"] if marshalling else [])]
    terms = np.column_stack([np.ones(len(s)), d**3, n * d**2 / p, *([n * d / p] if marshalling else [])])
    used = list(range(terms.shape[1]))
    while True:  # drop a term that would count negatively
        b = np.linalg.lstsq(terms[:, used] / terms[:, used].max(0), s, rcond=None)[0] / terms[:, used].max(0)
        if (b >= 0).all() or len(used) == 1:
            break
        used.pop(int((b * terms[:, used].max(0)).argmin()))
    full = np.zeros(terms.shape[1])
    full[used] = b
    rest = s - terms @ full
    return {k: float(v) for k, v in zip(names, full)} | {"r2": float(1 - (rest @ rest) / max(1e-300, ((s - s.mean()) ** 2).sum()))}

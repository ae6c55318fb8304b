"""Distribution functions: normal, Student t, chi-squared and F, with tails computed directly."""

from __future__ import annotations

import math

TINY = 1e-300


def norm_cdf(z: float) -> float:
    return 0.5 * math.erfc(-z / math.sqrt(2))


def norm_sf(z: float) -> float:
    return 0.5 * math.erfc(z / math.sqrt(2))


def norm_two_sided(z: float) -> float:
    return math.erfc(abs(z) / math.sqrt(2))


def _beta_fraction(a: float, b: float, x: float) -> float:
    """Continued fraction of the incomplete beta function, by the modified Lentz scheme."""
    c, d = 1.0, 1.0 - (a + b) * x / (a + 1)
    d = 1 / (d if abs(d) > TINY else TINY)
    h = d
    for m in range(1, 500):
        for term in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1 + term * d
            c = 1 + term / c
            d = 1 / (d if abs(d) > TINY else TINY)
            c = c if abs(c) > TINY else TINY
            h *= d * c
        if abs(d * c - 1) < 1e-16:
            break
    return h


def beta_inc(a: float, b: float, x: float) -> float:
    """Regularised incomplete beta function; its front factor is taken in logarithms."""
    if x <= 0 or x >= 1:
        return 0.0 if x <= 0 else 1.0
    front = math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x)
    if x < (a + 1) / (a + b + 2):
        return math.exp(front) * _beta_fraction(a, b, x) / a
    return 1 - math.exp(front) * _beta_fraction(b, a, 1 - x) / b


def t_two_sided(t: float, df: float) -> float:
    """P(|T| >= |t|), without the rounding floor of one minus a distribution function."""
    if not math.isfinite(t):
        return 0.0 if math.isinf(t) else math.nan
    return beta_inc(df / 2, 0.5, df / (df + t * t))


def t_cdf(t: float, df: float) -> float:
    tail = t_two_sided(t, df) / 2
    return 1 - tail if t > 0 else tail


def gamma_inc(a: float, x: float) -> tuple[float, float]:
    """Regularised lower and upper incomplete gamma functions."""
    if x <= 0:
        return 0.0, 1.0
    front = math.exp(a * math.log(x) - x - math.lgamma(a)) if a * math.log(x) - x - math.lgamma(a) > -745 else 0.0
    if x < a + 1:
        term = total = 1 / a
        n = a
        while abs(term) > abs(total) * 1e-17:
            n += 1
            term *= x / n
            total += term
        return total * front, 1 - total * front
    b = x + 1 - a
    c, d = 1 / TINY, 1 / b
    h = d
    for i in range(1, 1000):
        an = -i * (i - a)
        b += 2
        d = 1 / (an * d + b or TINY)
        c = b + an / c or TINY
        h *= d * c
        if abs(d * c - 1) < 1e-16:
            break
    return 1 - front * h, front * h


def chi2_cdf(x: float, df: float) -> float:
    return gamma_inc(df / 2, x / 2)[0]


def chi2_sf(x: float, df: float) -> float:
    return gamma_inc(df / 2, x / 2)[1]


def f_sf(x: float, d1: float, d2: float) -> float:
    return beta_inc(d2 / 2, d1 / 2, d2 / (d2 + d1 * x)) if x > 0 else 1.0


def f_cdf(x: float, d1: float, d2: float) -> float:
    return beta_inc(d1 / 2, d2 / 2, d1 * x / (d1 * x + d2)) if x > 0 else 0.0


def quantile(cdf, p: float, low: float = -1e3, high: float = 1e3) -> float:
    """The point at which a rising distribution function reaches p, by bisection; the range widens as needed."""
    if not 0 < p < 1:
        raise ValueError("p must lie between 0 and 1")
    while cdf(low) > p:
        low *= 2
    while cdf(high) < p:
        high *= 2
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (mid, high) if cdf(mid) < p else (low, mid)
        if high - low <= 1e-14 * max(1.0, abs(mid)):
            break
    return (low + high) / 2

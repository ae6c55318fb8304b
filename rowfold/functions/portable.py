"""Random numbers and hashes that any engine computes alike, from 64-bit arithmetic alone."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

M = 2147483647


def mixed(*terms: Column | int) -> Column:
    """A number in [0, M) from integers: a linear form, squared, run through a multiplicative generator."""
    form = sum(((t if isinstance(t, Column) else F.lit(t)).cast("long") * w for t, w in zip(terms, (7919, 104729, 1299709))), F.lit(12345).cast("long"))
    v = F.pmod(form, F.lit(M))
    return F.pmod(F.pmod(v * v + F.lit(12345), F.lit(M)) * F.lit(16807), F.lit(M))


def uniform(*terms: Column | int) -> Column:
    return mixed(*terms) / F.lit(float(M))


def mixed_sql(*terms: str) -> str:
    form = " + ".join(f"cast({t} as bigint) * {w}" for t, w in zip(terms, (7919, 104729, 1299709)))
    v = f"(({form} + 12345) % {M})"
    return f"((({v} * {v} + 12345) % {M}) * 16807) % {M}"


def uniform_sql(*terms: str) -> str:
    return f"({mixed_sql(*terms)}) / {M}.0::double"


def carter_wegman(x: Column, row: int, width: int) -> Column:
    """Row `row` of a family of pairwise independent hashes of integers below M into [0, width)."""
    a, b = 16807 * (2 * row + 1) + 11, 48271 * (row + 3) + 7
    return F.pmod(F.pmod(F.pmod(x.cast("long"), F.lit(M)) * a + b, F.lit(M)), F.lit(width))


def carter_wegman_sql(x: str, row: int | str, width: int) -> str:
    return f"(((cast({x} as bigint) % {M}) * (16807 * (2 * {row} + 1) + 11) + 48271 * ({row} + 3) + 7) % {M}) % {width}"

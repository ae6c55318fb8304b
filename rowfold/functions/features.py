"""Feature vectors from columns: one-hot, interactions, standardising, hashing, and guards for numbers that are not finite."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rowfold.core.validate import InputError, columns
from rowfold.functions.portable import M


def assemble(*parts: Column | str, intercept: bool = False) -> Column:
    """One vector of numbers and vectors, in order; null if any part is."""
    one = lambda p: F.col(p) if isinstance(p, str) else p
    arrays = [F.array(F.lit(1.0))] if intercept else []
    return F.concat(*arrays, *[one(p) for p in parts])


def number(c: Column | str) -> Column:
    """A number as a vector of one."""
    c = F.col(c) if isinstance(c, str) else c
    return F.when(c.isNotNull(), F.array(c.cast("double")))


def categories(df: DataFrame, col: str, most: int = 1000) -> list:
    """The values of a categorical column in order, of which there may be at most `most`."""
    got = [r[0] for r in df.select(col).filter(F.col(col).isNotNull()).distinct().orderBy(col).limit(most + 1).collect()]
    if len(got) > most:
        raise InputError("TOO_MANY_VALUES", f"{col} has over {most} values", "hash it instead")
    return got


def one_hot(col: str, values: Sequence, drop_first: bool = False) -> Column:
    """1 in the place of the row's value; all 0 for others and null."""
    return F.array(*[F.coalesce((F.col(col) == F.lit(v)).cast("double"), F.lit(0.0)) for v in list(values)[int(drop_first) :]])


def interaction(a: Column, b: Column) -> Column:
    """Products of every component of one vector with every one of another, the first's components outermost."""
    return F.flatten(F.transform(a, lambda x: F.transform(b, lambda y: x * y)))


def hashed(col: str, width: int, salt: int = 0) -> Column:
    """A value's place among `width` by the portable hash of its characters, as a vector with 1 or -1 there."""
    code = F.aggregate(F.split(F.col(col).cast("string"), ""), F.lit(salt + 17).cast("long"), lambda h, c: F.pmod(h * 131 + F.ascii(c), F.lit(M).cast("long")))
    at, sign = F.pmod(code, F.lit(width)), F.when(F.pmod(F.floor(code / width), F.lit(2)) == 0, 1.0).otherwise(-1.0)
    return F.transform(F.sequence(F.lit(0), F.lit(width - 1)), lambda i: F.when(i == at, sign).otherwise(F.lit(0.0)))


def moments(df: DataFrame, cols: Sequence[str]) -> dict[str, tuple[float, float]]:
    """Mean and standard deviation (of the rows, divided by n) of each column, in one pass."""
    columns(df, *cols)
    r = df.agg(*[f(F.col(c).cast("double")).alias(f"{k}_{i}") for i, c in enumerate(cols) for k, f in (("m", F.avg), ("s", F.stddev_pop))]).first()
    return {c: (r[f"m_{i}"] or 0.0, r[f"s_{i}"] or 0.0) for i, c in enumerate(cols)}


def standardise(df: DataFrame, cols: Sequence[str]) -> DataFrame:
    """Columns less their mean, over their standard deviation; constant ones become 0."""
    m = moments(df, cols)
    return df.withColumns({c: (F.col(c).cast("double") - m[c][0]) / (m[c][1] or 1.0) for c in cols})


def finite(c: Column) -> Column:
    """Whether a number, or every component of a vector of doubles, is there and finite."""
    return c.isNotNull() & ~F.isnan(c) & (F.abs(c) != float("inf"))


def finite_vector(x: Column) -> Column:
    return x.isNotNull() & F.forall(x, lambda v: F.coalesce(finite(v), F.lit(False)))


def guarded(df: DataFrame, vectors: Sequence[str] = (), numbers: Sequence[str] = (), policy: str = "drop") -> tuple[DataFrame, dict[str, int]]:
    """(rows that are whole, number of rows with a null or a number that is not finite, by column). policy: drop such rows,
    or raise an error with their number."""
    if policy not in ("drop", "error"):
        raise InputError("UNKNOWN_POLICY", f"no policy {policy!r}", "drop or error")
    columns(df, *vectors, *numbers)
    good = {c: finite_vector(F.col(c).cast("array<double>")) for c in vectors} | {c: F.coalesce(finite(F.col(c).cast("double")), F.lit(False)) for c in numbers}
    r = df.agg(*[F.coalesce(F.sum((~g).cast("long")), F.lit(0)).alias(f"g{i}") for i, g in enumerate(good.values())]).first()
    bad = {c: r[f"g{i}"] for i, c in enumerate(good)}
    if policy == "error" and any(bad.values()):
        raise InputError("NOT_FINITE", ", ".join(f"{c}: {n} rows" for c, n in bad.items() if n), "drop or mend these rows")
    for g in good.values():
        df = df.filter(g)
    return df, bad

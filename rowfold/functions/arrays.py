"""Array operators as column expressions; null elements count as missing, lengths must agree."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _d(x: Column | str) -> Column:
    return (F.col(x) if isinstance(x, str) else x).cast("array<double>")


def total(x) -> Column:
    return F.aggregate(_d(x), F.lit(0.0), lambda s, v: s + v)


def dot(x, y) -> Column:
    return total(F.zip_with(_d(x), _d(y), lambda a, b: a * b))


def add(x, y) -> Column:
    return F.zip_with(_d(x), _d(y), lambda a, b: a + b)


def sub(x, y) -> Column:
    return F.zip_with(_d(x), _d(y), lambda a, b: a - b)


def mult(x, y) -> Column:
    return F.zip_with(_d(x), _d(y), lambda a, b: a * b)


def div(x, y) -> Column:
    """Elementwise quotient; null where the divisor is 0."""
    return F.zip_with(_d(x), _d(y), lambda a, b: F.try_divide(a, b))


def scalar(x, op: str, c: float) -> Column:
    ops = {"add": lambda v: v + c, "sub": lambda v: v - c, "mult": lambda v: v * c, "div": lambda v: v / c, "pow": lambda v: F.pow(v, F.lit(float(c)))}
    return F.transform(_d(x), ops[op])


def sum_abs(x) -> Column:
    return total(F.transform(_d(x), F.abs))


def mean(x) -> Column:
    return F.try_divide(total(x), F.size(_d(x)))


def std(x) -> Column:
    """Sample standard deviation; null below two elements."""
    m = mean(x)
    return F.when(F.size(_d(x)) > 1, F.sqrt(total(F.transform(_d(x), lambda v: (v - m) * (v - m))) / (F.size(_d(x)) - 1)))


def minimum(x) -> Column:
    return F.array_min(_d(x))


def maximum(x) -> Column:
    return F.array_max(_d(x))


def argmin(x) -> Column:
    """Place of the least element, from 0; the first on ties."""
    return F.array_position(_d(x), F.array_min(_d(x))) - 1


def argmax(x) -> Column:
    return F.array_position(_d(x), F.array_max(_d(x))) - 1


def sqrt(x) -> Column:
    return F.transform(_d(x), F.sqrt)


def square(x) -> Column:
    return F.transform(_d(x), lambda v: v * v)


def norm1(x) -> Column:
    return sum_abs(x)


def norm2(x) -> Column:
    return F.sqrt(dot(x, x))


def normalise(x) -> Column:
    n = norm2(x)
    return F.transform(_d(x), lambda v: F.try_divide(v, n))


def cosine(x, y) -> Column:
    return F.try_divide(dot(x, y), norm2(x) * norm2(y))


def euclid(x, y) -> Column:
    return norm2(sub(x, y))


def fill(n: int, value: float) -> Column:
    return F.array_repeat(F.lit(float(value)), n)


def contains(x, y) -> Column:
    """Whether every element of y is among those of x."""
    return F.forall(_d(y), lambda v: F.array_contains(_d(x), v))


def keep_if(x, pred) -> Column:
    return F.filter(_d(x), pred)


def unnest(df: DataFrame, col: str) -> DataFrame:
    """Rows of a two-dimensional array: (other columns, row, values)."""
    return df.select(*[c for c in df.columns if c != col], F.posexplode(col).alias("row", "values"))


def aggregate_arrays(df: DataFrame, col: str, by: tuple[str, ...] = (), what: str = "sum") -> DataFrame:
    """Elementwise sum, avg, min or max of all rows' arrays: (by, values), aggregated by place before it is gathered."""
    f = {"sum": F.sum, "avg": F.avg, "min": F.min, "max": F.max}[what]
    each = df.select(*by, F.posexplode(_d(col)).alias("p", "v")).groupBy(*by, "p").agg(f("v").alias("v"))
    return each.groupBy(*by).agg(F.transform(F.array_sort(F.collect_list(F.struct("p", "v"))), lambda s: s["v"]).alias("values"))

"""Functions for SQL callers."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf

from rowfold.core.bridge import unpacked
from rowfold.functions import dist
from rowfold.operators.ols import RESULT, solve


def ols_select(y: str, xs: list[str], table: str, by: str | None = None) -> str:
    """A SELECT whose column r is the composite result of least squares: generated sums and one finishing call, so it may be
    grouped like any aggregate."""
    d = len(xs)
    xy = ", ".join(f"sum({x} * {y})" for x in xs)
    g = ", ".join(f"sum({xs[i]} * {xs[j]})" for i in range(d) for j in range(i + 1))
    call = f"ols_finish(count(*), cast(sum({y}) as double), cast(sum({y} * {y}) as double), array({xy}), array({g})) AS r"
    return f"SELECT {by + ', ' if by else ''}{call} FROM {table}" + (f" GROUP BY {by}" if by else "")


def register_all(spark: SparkSession) -> list[str]:
    @pandas_udf(RESULT)
    def ols_finish(n: pd.Series, sy: pd.Series, syy: pd.Series, xy: pd.Series, g: pd.Series) -> pd.DataFrame:
        rows = [solve(float(a), b, c, np.array(x, float), unpacked(np.array(t, float), len(x)), int(a)) for a, b, c, x, t in zip(n, sy, syy, xy, g)]
        return pd.DataFrame(rows)

    @pandas_udf("double")
    def t_two_sided(t: pd.Series, df: pd.Series) -> pd.Series:
        return pd.Series([dist.t_two_sided(float(a), float(b)) for a, b in zip(t, df)])

    @pandas_udf("double")
    def norm_two_sided(z: pd.Series) -> pd.Series:
        return z.map(lambda v: dist.norm_two_sided(float(v)))

    @pandas_udf("double")
    def chi2_sf(x: pd.Series, df: pd.Series) -> pd.Series:
        return pd.Series([dist.chi2_sf(float(a), float(b)) for a, b in zip(x, df)])

    @pandas_udf("int")
    def nearest_centre(x: pd.Series, centres: pd.Series) -> pd.Series:
        return pd.Series([int(np.round(((np.array([*c]) - np.array(v)) ** 2).sum(1), 10).argmin()) for v, c in zip(x, centres)])

    @udtf(returnType="pos int, token string")
    class tokenize:  # noqa: N801
        def eval(self, text: str):
            for i, t in enumerate((text or "").split()):
                yield i, t

    from pyspark.sql.functions import AnalyzeArgument, AnalyzeResult
    from pyspark.sql.types import LongType, StringType, StructType

    @udtf
    class profile_part:  # noqa: N801
        """For each column of a table argument, of the rows that one task sees: rows, nulls, the least and greatest value as
        text, and characters. Tasks' rows add up by column."""

        @staticmethod
        def analyze(t: AnalyzeArgument) -> AnalyzeResult:
            if not t.isTable:
                raise ValueError("profile_part takes a table")
            out = StructType().add("column", StringType()).add("n", LongType()).add("nulls", LongType()).add("chars", LongType()).add("least", StringType()).add("greatest", StringType())
            return AnalyzeResult(schema=out)

        def __init__(self):
            self.seen: dict = {}

        def eval(self, row):
            for c, v in row.asDict().items():
                s = self.seen.setdefault(c, [0, 0, 0, None, None])
                s[0] += 1
                if v is None:
                    s[1] += 1
                    continue
                s[2] += len(str(v))
                s[3] = v if s[3] is None or v < s[3] else s[3]
                s[4] = v if s[4] is None or v > s[4] else s[4]

        def terminate(self):
            for c, (n, nulls, chars, low, high) in self.seen.items():
                yield c, n, nulls, chars, None if low is None else str(low), None if high is None else str(high)

    for f, name in ((ols_finish, "ols_finish"), (t_two_sided, "t_two_sided"), (norm_two_sided, "norm_two_sided"), (chi2_sf, "chi2_sf"), (nearest_centre, "nearest_centre")):
        spark.udf.register(name, f)
    spark.udtf.register("tokenize", tokenize)
    spark.udtf.register("profile_part", profile_part)
    return ["ols_finish", "t_two_sided", "norm_two_sided", "chi2_sf", "nearest_centre", "tokenize", "profile_part"]


def flatten_result(df: DataFrame, as_: str = "columns") -> DataFrame:
    """Nested results for callers without nested types: arrays become columns, JSON or text."""
    if as_ == "json":
        return df.select(F.to_json(F.struct(*df.columns)).alias("result"))
    if as_ == "string":
        return df.select(*[F.concat_ws(",", F.transform(c, lambda v: v.cast("string"))).alias(c) if t.startswith("array") else F.col(c).cast("string").alias(c) for c, t in df.dtypes])
    sizes = df.select(*[F.max(F.size(c)).alias(c) for c, t in df.dtypes if t.startswith("array")]).first()
    out = []
    for c, t in df.dtypes:
        out += [F.get(c, F.lit(i)).alias(f"{c}_{i}") for i in range(sizes[c] or 0)] if t.startswith("array") else [F.col(c)]
    return df.select(*out)

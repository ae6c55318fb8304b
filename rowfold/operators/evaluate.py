"""Accuracy measures as aggregates."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def confusion(df: DataFrame, truth: str, guess: str) -> DataFrame:
    return df.groupBy(F.col(truth).alias("truth"), F.col(guess).alias("guess")).agg(F.count("*").alias("n"))


def accuracy(df: DataFrame, truth: str, guess: str) -> DataFrame:
    return df.agg(F.avg((F.col(truth) == F.col(guess)).cast("double")).alias("accuracy"))


def rmse(df: DataFrame, truth: str, guess: str) -> DataFrame:
    return df.agg(F.sqrt(F.avg((F.col(truth) - F.col(guess)) ** 2)).alias("rmse"))


def auc(df: DataFrame, truth: str, score: str, digits: int = 4) -> DataFrame:
    """Area under the curve from counts by distinct score; ties count one half. Scores count to so many digits, which bounds
    what is ordered on one task: 10,000 rows for probabilities, whatever the rows."""
    by = df.groupBy(F.round(score, digits).alias("s")).agg(F.sum(F.col(truth).cast("long")).alias("p"), F.sum(1 - F.col(truth).cast("long")).alias("n"))
    below = F.coalesce(F.sum("n").over(Window.orderBy("s").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return by.withColumn("b", below).agg((F.sum(F.col("p") * (F.col("b") + F.col("n") / 2)) / (F.sum("p") * F.sum("n"))).alias("auc"))


def prf(found: DataFrame, truth: DataFrame, keys: list[str]) -> DataFrame:
    """Precision, recall and F1 of one set of keys against another."""
    f, t = found.select(*keys).distinct().withColumn("f", F.lit(1)), truth.select(*keys).distinct().withColumn("t", F.lit(1))
    c = f.join(t, keys, "full").agg(F.count(F.when((F.col("f") == 1) & (F.col("t") == 1), 1)).alias("hit"), F.count("f").alias("nf"), F.count("t").alias("nt"))
    p, r = F.try_divide("hit", "nf"), F.try_divide("hit", "nt")
    return c.select("hit", "nf", "nt", p.alias("precision"), r.alias("recall"), F.try_divide(2 * p * r, p + r).alias("f1"))


def marginal_error(estimated: DataFrame, exact: DataFrame) -> DataFrame:
    """Largest and mean distance of (doc_id, pos, label, p) from exact marginals."""
    j = exact.select("doc_id", "pos", "label", F.col("p").alias("q")).join(estimated, ["doc_id", "pos", "label"], "left")
    return j.agg(F.max(F.abs(F.coalesce("p", F.lit(0.0)) - F.col("q"))).alias("worst"), F.avg(F.abs(F.coalesce("p", F.lit(0.0)) - F.col("q"))).alias("mean"))


def sketch_error(estimated: DataFrame, true: DataFrame, key: str, estimate: str = "estimate", count: str = "n") -> DataFrame:
    """(worst, mean, exact, below): how far estimates lie from true counts, the share that is exact, and how many fall below."""
    e = true.join(estimated, key, "left").withColumn("e", F.coalesce(estimate, F.lit(0)) - F.col(count))
    return e.agg(F.max(F.abs("e")).alias("worst"), F.avg(F.abs("e").cast("double")).alias("mean"), F.avg((F.col("e") == 0).cast("double")).alias("exact"), F.sum((F.col("e") < 0).cast("long")).alias("below"))

"""Connected components by alternating stars, with every round staged in the shared folder."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowfold.llm.common import staged


def components(links: DataFrame, most: int = 60) -> DataFrame:
    """(node, comp) for the nodes of links (a, b): comp is the least node reachable.

    Each round hangs every larger neighbour on the least neighbour of its node, then every smaller neighbour on
    the least of them; rounds grow with the logarithm of the nodes. Only one number a round comes to the driver.
    """
    e = links.filter("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    e = staged(e, "cc")
    before = None
    for i in range(most):
        both = e.select("u", "v").unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        down = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(down, "u").select("v", "m").filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(down.select("u", F.col("m").alias("v"))).distinct()
        e = staged(small, f"cc{i}")
        now = e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == before:
            break
        before = now
    else:
        raise RuntimeError("components did not settle")
    own = e.select(F.col("u").alias("node"), F.col("v").alias("comp"))
    return own.unionByName(e.select(F.col("v").alias("node"), F.col("v").alias("comp")).distinct()).groupBy("node").agg(F.min("comp").alias("comp"))

"""What a plan will do, as counts that tests can hold."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def text(df: DataFrame, mode: str = "formatted") -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString(mode))


def stats(df: DataFrame) -> dict:
    """Exchanges, broadcasts, sorts, Python and Arrow nodes, row-at-a-time Python, and the columns read."""
    t = text(df, "simple")
    count = lambda p: len(re.findall(p, t))
    reads = re.findall(r"ReadSchema: struct<([^>]*)>", t)
    return {
        "exchanges": count(r"(?m)^[ :+\-|*()0-9]*Exchange "), "broadcasts": count("BroadcastExchange"), "sorts": count(r"(?m)^[ :+\-|*()0-9]*Sort "),
        "arrow": count("MapInArrow|FlatMapGroupsInArrow|FlatMapCoGroupsInArrow|ArrowEvalPython"), "row_python": count("BatchEvalPython"), "cartesian": count("CartesianProduct|BroadcastNestedLoopJoin"),
        "columns": sorted({c.split(":")[0] for r in reads for c in r.split(",") if c}), "pushed": re.findall(r"PushedFilters: \[([^\]]*)\]", t),
    }

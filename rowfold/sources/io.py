"""Readers and sinks, and a store for models."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession


def read(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """parquet, csv, json, orc, text or xml; with a schema nothing is inferred."""
    r = spark.read.format(fmt).options(**options)
    return (r.schema(schema) if schema else r).load(path)


def values(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def save(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "error", partition_by: tuple[str, ...] = (), **options) -> None:
    w = df.write.format(fmt).mode(mode).options(**options)
    (w.partitionBy(*partition_by) if partition_by else w).save(path)


def save_clustered(df: DataFrame, path: str, by: str, mode: str = "error") -> None:
    """Files ordered by `by`, so that readers can prune row groups by its least and greatest values."""
    df.repartitionByRange(by).sortWithinPartitions(by).write.mode(mode).parquet(path)


def jdbc(spark: SparkSession, url: str, query: str, column: str | None = None, low: int = 0, high: int = 0, parts: int = 1, **options) -> DataFrame:
    """A table in a database, read in ranges of a numeric column."""
    r = spark.read.format("jdbc").option("url", url).option("dbtable", f"({query}) t").options(**options)
    if column:
        r = r.option("partitionColumn", column).option("lowerBound", low).option("upperBound", high).option("numPartitions", parts)
    return r.load()


def save_model(tables: dict[str, DataFrame], path: str, meta: dict) -> None:
    """Model tables as Parquet beside their metadata, which is written last and so marks the model whole."""
    spark = next(iter(tables.values())).sparkSession
    for name, df in tables.items():
        df.write.mode("overwrite").parquet(f"{path}/{name}")
    spark.createDataFrame([(json.dumps(meta | {"tables": sorted(tables)}),)], "meta string").coalesce(1).write.mode("overwrite").json(f"{path}/_meta")


def load_model(spark: SparkSession, path: str) -> tuple[dict[str, DataFrame], dict]:
    meta = json.loads(spark.read.json(f"{path}/_meta").first()["meta"])
    return {n: spark.read.parquet(f"{path}/{n}") for n in meta["tables"]}, meta

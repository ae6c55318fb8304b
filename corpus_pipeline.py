"""The corpus pipeline: five stages, each on all that the one before kept.

A stage takes (spark, docs, sf_dir) and returns a DataFrame; docs has the columns of
documents, and so have the results of all stages but the last. Each result is
written as Parquet and read again as the next stage's docs.

Decisions are tied to a row's id and text together, so rows without an id, and unlike
texts under one id, are each treated by their own text; rows that repeat both
share a decision. Further columns are dropped; an empty table stays empty.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rowfold.llm import pieces
from rowfold.llm.common import staged, table
from rowfold.llm.decontaminate import contaminated
from rowfold.llm.jaccard import jaccard_groups
from rowfold.llm.pii import find_pii, redacted
from rowfold.llm.quality import classify
from rowfold.llm.queries import PIECE_MODEL

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def keyed(docs: DataFrame) -> DataFrame:
    """docs with a key that names a row's id and text, in order of id, without an id last."""
    key = F.struct(F.col("doc_id").isNull().alias("none"), F.coalesce("doc_id", F.lit(0)).cast("long").alias("doc_id"), F.xxhash64("text").alias("text_key"))
    return docs.select(*COLUMNS).withColumn("key", key)


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go, and with them those without text."""
    docs = keyed(docs)
    kept = classify(docs, table(spark, sf_dir, "labels"), carry=("key",)).filter("keep").select("key").distinct()
    return docs.join(kept, "key", "left_semi").select(*COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near duplicates the document with the least id stays; of rows that repeat id and text, one."""
    docs = keyed(docs)
    first = jaccard_groups(docs, id_col="key").filter("key = component_id").select("key").distinct()
    return docs.join(first, "key", "left_semi").dropDuplicates(["key"]).select(*COLUMNS)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that overlap an item of the benchmark go."""
    docs = keyed(docs)
    hit = contaminated(docs.select(F.col("key").alias("doc_id"), "text"), table(spark, sf_dir, "benchmark")).select(F.col("doc_id").alias("key")).distinct()
    return docs.join(hit, "key", "left_anti").select(*COLUMNS)


def private_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every span of personal data becomes its kind in angle brackets; n_chars follows the new text. Where spans overlap,
    their union is replaced, by the kind of the first."""
    docs = keyed(docs)
    spans = find_pii(docs, id_col="key").filter("spans <> ''").select("key", "spans").dropDuplicates(["key"])
    return redacted(docs.join(spans, "key", "left").select(*COLUMNS, "spans")).select(*COLUMNS)


def encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Piece ids of every document, decoded again and compared."""
    return pieces.encode(docs, PIECE_MODEL)


STAGES = [
    ("quality classifier", quality),
    ("n-gram Jaccard join", near_duplicates),
    ("benchmark decontamination", decontamination),
    ("PII", private_data),
    ("SentencePiece encoding and decoding", encoding),
]

#: A trained model and its encoding are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; what each keeps is written and read again."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if stage is not encoding:
            docs = staged(docs, "pipeline-" + name.split()[0])
    return docs

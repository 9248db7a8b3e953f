"""Corpus preparation in four stages, each written as Parquet and read again as the next one's documents.

Texts of low quality go, one document of each group of near duplicates stays (five-word shingles,
similarity 0.8 or more, the smallest id), secrets are replaced by a mask, and what is left is packed into
training sequences. Every stage but the last returns the columns it was given.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shardwise.llm import jaccard, packing, quality, secrets
from shardwise.llm.common import small, stored, table, tokenizer_path


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep the documents that the classifier accepts."""
    model = quality.train(docs, table(spark, sf_dir, "labels"))
    scored = quality.score(docs, model, keep=tuple(docs.columns))
    return scored.where("predicted = 1").select(*docs.columns)


def duplicates_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep one row of each component, one with the smallest id (null ids last); ids may repeat, rows are told apart by a number of their own."""
    rows = stored(docs.withColumn("_row", F.monotonically_increasing_id()), "rows")
    found = jaccard.near_duplicates(rows, jaccard.Rule(words=5, percent=80), id_col="_row")
    order = F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "_row")
    least = found.select("_row", "component_id").join(rows.select("_row", "doc_id"), "_row").groupBy("component_id").agg(F.min(order).alias("least"))
    gone = stored(rows.select("_row").join(least.select("least._row"), "_row", "left_anti"), "gone")
    return rows.join(small(gone, gone.count()), "_row", "left_anti").select(*docs.columns)


def secrets_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replace secrets; n_chars follows the text where it changed."""
    clean = secrets.redact(docs.withColumn("_before", F.col("text")))
    changed = ~F.col("text").eqNullSafe(F.col("_before"))
    return clean.withColumn("n_chars", F.when(changed, F.length("text").cast("long")).otherwise(F.col("n_chars"))).select(*docs.columns)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pack the texts; one row per piece."""
    return packing.pack(docs, tokenizer_path("word_bpe_49k.json"))


STAGES = [
    ("quality classifier", quality_stage),
    ("n-gram Jaccard join", duplicates_stage),
    ("secret scans", secrets_stage),
    ("packing", packing_stage),
]

#: Neither the classifier's scores nor the packing can be expressed in SQL; tests compare with plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents of sf_dir."""
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = stored(docs, f"stage{k + 1}")
    return docs

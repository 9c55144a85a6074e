"""The corpus pipeline: quality rules, line removal, near-duplicate join, redaction, packing.

Each stage takes (spark, docs, sf_dir), works on all rows that its predecessor kept and returns the columns of
documents (the last one: pieces with their places). run() writes each result as Parquet in the shared folder and reads it
again. Decisions are made on rows, not ids: rows that share an id, or have none, are judged by their own texts.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from boxprune.llm.jaccard import jaccard_classes, row_key
from boxprune.llm.lines import LARGE, drop_boilerplate
from boxprune.llm.packing import pack_documents
from boxprune.llm.pii import redact
from boxprune.llm.quality import keep_good
from boxprune.llm.shared import small_side, stored

#: Near-duplicate stage: five-word shingles at a similarity of 0.8.
SHINGLE_WORDS, SIMILARITY = 5, (80, 100)


#: Keys of rows that may be broadcast (about 100 bytes each).
BROADCAST_KEYS = 300_000


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return keep_good(docs)


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return drop_boilerplate(docs, large=LARGE)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each class stays: the one with the smallest id, ids that are null last. Of rows with equal id and text,
    one stays. Rows without words are in no class and stay."""
    key = "__boxprune_key"
    classes = stored(jaccard_classes(docs, k=SHINGLE_WORDS, num=SIMILARITY[0], den=SIMILARITY[1]).where("n > 0"))
    gone = stored(classes.where(~F.col("key").eqNullSafe(F.col("least"))).select(F.col("key").alias(key)).distinct())
    twice = stored(classes.where(F.col("key").eqNullSafe(F.col("least"))).groupBy(F.col("key").alias(key)).agg(F.count(F.lit(1)).alias("n")).where("n > 1").select(key))
    keyed = docs.withColumn(key, row_key())
    left = keyed.join(small_side(gone, BROADCAST_KEYS), key, "left_anti")
    if twice.limit(1).count():
        once = left.join(twice, key, "left_semi").dropDuplicates([key])
        left = left.join(twice, key, "left_anti").unionByName(once)
    return left.select(*docs.columns)


def pii_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return redact(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack_documents(docs, public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.PATTERN)


STAGES = [
    ("quality_rules", quality_stage),
    ("line_dedup", line_stage),
    ("jaccard_join", near_duplicate_stage),
    ("pii", pii_stage),
    ("packing", packing_stage),
]

#: SQL can't express the fitted stages; tests hold run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES:
        docs = stored(stage(spark, docs, sf_dir))
    return docs

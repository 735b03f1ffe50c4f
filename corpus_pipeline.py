"""Corpus cleaning: quality rules, near-duplicate join, repeated-string removal, benchmark decontamination, byte-level BPE.

Every stage takes and returns the columns of documents, the last returns ids per document.  Verdicts are on rows: a doc_id may be null or be there
with several texts, each row that is clean stays.  A row without doc_id is a near duplicate of nothing; of equal rows of one doc_id one stays.
A document of which repeated strings leave nothing goes too; characters cut in two are left out.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from triadspark.llm.bpe_sql import bpe_round_trip
from triadspark.llm.common import stored, table
from triadspark.llm.decontamination import find_items
from triadspark.llm.jaccard_join import jaccard_components
from triadspark.llm.quality_rules import judge_quality
from triadspark.llm.suffix_dedup import suffix_dedup

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def _keyed(docs: DataFrame) -> DataFrame:
    """docs with a key that only rows of equal doc_id and text share."""
    return docs.withColumn("_key", F.xxhash64("doc_id", F.col("doc_id").isNull(), "text", F.col("text").isNull()))


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    rows = _keyed(docs.select(COLUMNS))
    kept = judge_quality(rows.select(F.col("_key").alias("doc_id"), "text", "lang")).where("kept").select(F.col("doc_id").alias("_key"))
    return rows.join(kept, "_key", "left_semi").select(COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    first = jaccard_components(docs).where("doc_id = component_id").select("doc_id")
    rows = _keyed(docs.select(COLUMNS))
    return rows.join(first, "doc_id", "left_semi").dropDuplicates(["doc_id", "_key"]).unionByName(rows.where("doc_id is null")).select(COLUMNS)


def repeated_strings(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    left = suffix_dedup(docs, with_text=True, carry=["lang", "source"]).where("n_removed < n_bytes or n_bytes = 0")
    return left.select("doc_id", F.col("kept_text").alias("text"), "lang", "source", F.length("kept_text").cast("long").alias("n_chars"))


def decontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    rows = _keyed(docs.select(COLUMNS))
    clean = find_items(rows.select(F.col("_key").alias("doc_id"), "text"), table(spark, sf_dir, "benchmark")).where("n_hit = 0").select(F.col("doc_id").alias("_key"))
    return rows.join(clean, "_key", "left_semi").select(COLUMNS)


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return bpe_round_trip(docs, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN, known=200_000, run_bytes=1 << 19)


STAGES = [("quality rules", quality), ("n-gram Jaccard join", near_duplicates), ("suffix-array dedup", repeated_strings), ("benchmark decontamination", decontaminated), ("byte-level BPE", encoded)]

#: substring removal and BPE are beyond SQL on whole tables
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = stored(docs, "stage-" + name.replace(" ", "-"))
    return docs

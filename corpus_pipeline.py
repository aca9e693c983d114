"""The corpus pipeline over ``documents``: five stages, each one operator of evsketch.llm.

Quality rules drop documents, near-dedup keeps one document of each group, suffix dedup cuts
passages that an earlier document has, PII is generalised, and best-fit packing places what is left
in sequences. Every stage but the last returns the columns of its input; each one's result is
written as Parquet and read again as the next one's.

Defined cases: null and empty texts fail the quality rules; repeated rows of one doc_id are one
document and stay or go together; an empty table gives no rows; other columns are passed through.
"""

from __future__ import annotations

import uuid

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evsketch.llm import minhash, packing, pii, quality, suffix
from evsketch.llm.common import shared_dir, ship, table

VOCABULARY = public_tokenizers.path("byte_bpe_50k.json")


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    return quality.keep_good(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Five-word shingles, similarity 0.8 or more."""
    ship(spark)
    return minhash.keep_one(docs)


def measured(docs: DataFrame) -> DataFrame:
    """n_chars, where there is such a column, follows the text that a stage has rewritten."""
    if "n_chars" not in docs.columns:
        return docs
    kind = docs.schema["n_chars"].dataType
    return docs.withColumn("n_chars", F.when(F.col("text").isNull(), F.col("n_chars")).otherwise(F.length("text").cast(kind)))


def suffix_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    return measured(suffix.cut_repeats(docs))


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    return measured(pii.sanitise(docs))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    return packing.pack(docs, VOCABULARY)


STAGES = [("quality_rules", quality_rules), ("near_dedup", near_dedup), ("suffix_dedup", suffix_dedup), ("pii", personal_data), ("packing", pack)]

#: SQL cannot express the stages; tests compare run() with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    root = f"{shared_dir(spark).rstrip('/')}/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{root}/{name}")
        docs = spark.read.parquet(f"{root}/{name}")
    return docs

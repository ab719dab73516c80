"""Training-data pipeline: quality, exact copies, near copies, mixing, tokens.

Each stage reads what the one before it wrote.  All but the last return the
columns of ``documents``; the last returns each document's token ids and the
digests of ids and decoded text.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from bitplane.llm import exact_dedup, mixing, near_dedup, quality, tokenizing
from bitplane.llm.common import driver_gives_back, scratch, table, vocabulary_path


def reject_low_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    good = quality.keep_good(docs, table(spark, sf_dir, "labels"))
    driver_gives_back(spark)  # the fits
    return good


def drop_exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return exact_dedup.dedup(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return near_dedup.dedup(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    mixed = mixing.mix(docs)
    driver_gives_back(spark)  # the raking's plans
    return mixed


def encode_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return tokenizing.round_trip(docs, vocabulary_path("word_bpe_49k.json"), keep_ids=True)


STAGES = [
    ("quality", reject_low_quality),
    ("exact_dedup", drop_exact_copies),
    ("near_dedup", drop_near_copies),
    ("mixing", mix_sources),
    ("bpe", encode_tokens),
]

#: Fitted weights and signatures have no SQL; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, written and read again in between."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        path = scratch(spark, f"stage-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return STAGES[-1][1](spark, docs, sf_dir)

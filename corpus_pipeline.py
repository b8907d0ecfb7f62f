"""The corpus pipeline: documents in, packed training sequences out.

language ID -> min-max hashing near-dedup -> secret scan -> mixing -> best-fit packing. Each
stage reads what its predecessor wrote; all but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dynreach.llm import language_id, minmax_dedup, mixing, packing, secret_scan
from dynreach.llm.common import cut


def known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that are rejected (no letters, or unlike every language learnt) go; a missing lang is filled in."""
    model = language_id.learn(docs)
    found = language_id.classify(docs, model, names=("__lang", "__score", "__rejected"))
    return found.where(~F.col("__rejected")).withColumn("lang", F.coalesce("lang", "__lang")).select(*docs.columns)


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest id of each group of near copies (shingle similarity 0.8 or more) stays."""
    return minmax_dedup.keep_one(docs, percent=80)


def without_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Spans of secrets are replaced; every document stays."""
    clean = secret_scan.redact(docs)
    return clean.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else clean


def in_proportion(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Small sources are repeated up to twice; every document stays at least once."""
    return mixing.mixed(docs, repeat_limit=2.0)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces with their ids, sequence and offset, and a number for each row packed, as mixing repeats documents.

    Workers keep fewer units and free them, as other stages share them.
    """
    return packing.pack(docs, with_ids=True, with_row=True, cache_bytes=32 << 20, shared=True)


STAGES = [
    ("language_id", known_language),
    ("minmax_dedup", one_of_each),
    ("secret_scan", without_secrets),
    ("mixing", in_proportion),
    ("packing", packed),
]

#: Packing needs a tokenizer, which SQL has not; tests hold each stage against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; what is between them is checkpointed, and so read again rather than made again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = cut(docs)
    return docs

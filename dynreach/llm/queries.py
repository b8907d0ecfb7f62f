"""Queries opN_<name> over whole tables, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dynreach.llm import cap_filters, language_id, minmax_dedup, mixing, one_bit_search, packing, prefix_tokens, secret_scan, sharding, sql, toxicity
from dynreach.llm.common import table


def op1_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return prefix_tokens.token_counts(table(spark, sf_dir, "documents"), limit=512)


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.assess(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.identify(table(spark, sf_dir, "documents"))


def op4_cap_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cap_filters.near_duplicates(table(spark, sf_dir, "embeddings"), least=0.93)


def op5_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), capacity=1024, end_id=2)


def op6_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.digest(table(spark, sf_dir, "documents"))


def op7_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "source", "text")
    drawn = mixing.permuted(docs.select("doc_id", "source", mixing.tokens().alias("n_tokens")), repeat_limit=2.0, token_count=F.col("n_tokens"))
    return drawn.select("doc_id", "source", "n_tokens", "mix_exponent", "mix_weight", "mix_blocks", "mix_last", "mix_copies", "mix_block", "mix_place")


def op8_minmax_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minmax_dedup.dedup(table(spark, sf_dir, "documents"), width=5, percent=85)


def op9_one_bit_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings")
    return one_bit_search.search(vectors, vectors.where("vec_id % 20 = 0"), k=20)


def op10_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.assign_shards(table(spark, sf_dir, "documents"), shards=8, law="rows")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_token_counts": op1_token_counts,
    "op2_toxicity": op2_toxicity,
    "op3_language_id": op3_language_id,
    "op4_cap_filters": op4_cap_filters,
    "op5_best_fit_packing": op5_best_fit_packing,
    "op6_secret_scan": op6_secret_scan,
    "op7_mixing": op7_mixing,
    "op8_minmax_dedup": op8_minmax_dedup,
    "op9_one_bit_search": op9_one_bit_search,
    "op10_sharding": op10_sharding,
}

ORACLE_SQL: dict[str, str] = {"op4_cap_filters": sql.OP4, "op6_secret_scan": sql.OP6, "op8_minmax_dedup": sql.OP8, "op9_one_bit_search": sql.OP9}

"""The registered queries of the corpus operators: each applies its operator to its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from keyloom.llm import byte_bpe, cap_filters, language_rank, license_scan, multiset_fingerprint, secret_cnn, shard_minimax, simhash_mih, source_mix, toxicity
from keyloom.llm.common import table


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.digest(table(spark, sf_dir, "documents"))


def op2_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return byte_bpe.digest(table(spark, sf_dir, "documents"))


def op3_cap_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cap_filters.digest(table(spark, sf_dir, "embeddings"))


def op4_language_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_rank.digest(table(spark, sf_dir, "documents"))


def op5_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return source_mix.taken(table(spark, sf_dir, "documents"))


def op6_minimax_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard_minimax.digest(table(spark, sf_dir, "documents"))


def op7_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash_mih.digest(table(spark, sf_dir, "documents"))


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.digest(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op9_multiset_fingerprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    return multiset_fingerprint.digest(table(spark, sf_dir, "documents"))


def op10_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_cnn.digest(table(spark, sf_dir, "documents"))


ALL = (op1_license_scan, op2_byte_bpe, op3_cap_filters, op4_language_rank, op5_source_mix, op6_minimax_shards, op7_simhash_near_dedup, op8_toxicity, op9_multiset_fingerprint, op10_secret_scan)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in ALL}


def oracle_sql() -> dict[str, str]:
    return {"op5_source_mix": source_mix.ORACLE}

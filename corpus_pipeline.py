"""The corpus pipeline: toxic documents go, one of each near-duplicate group stays, secrets are masked, sources are mixed, texts are encoded.

Each stage takes (spark, docs, sf_dir) and returns the columns of ``documents``, the last one token ids. Null texts are neither toxic nor duplicates and hold no secrets;
the mix takes them, as texts without words, by their place in its order, and they get no tokens. Empty and blank texts are one group of duplicates. An empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from keyloom.llm import byte_bpe, secret_cnn, simhash_mih, source_mix, toxicity
from keyloom.llm.common import table, written

#: XXH64 fingerprints and the models of the first and third stage can't be put in SQL; tests/llm compares the stages with brute force.
ORACLE_SQL = None


def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that score 0.5 or more go. The model is learnt from the labelled ones that op8 may learn from."""
    model = toxicity.learn(docs, table(spark, sf_dir, "labels"), ~toxicity.held_out())
    return toxicity.reject(docs, model)


def near_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group stays: that of the smallest id. Documents without a text stay, too."""
    return simhash_mih.keep_one(docs)


def secret_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets in texts are masked, and n_chars follows; no document goes."""
    clean = secret_cnn.redact(docs)
    return clean.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else clean


def mix_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document comes as many times as the mix takes it."""
    return source_mix.mix(docs)


def encode_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, n_tokens, ids) of each row."""
    return byte_bpe.encode(docs)


STAGES = [("toxicity", toxicity_stage), ("simhash_near_dedup", near_dedup_stage), ("secret_scan", secret_stage), ("source_mix", mix_stage), ("byte_bpe", encode_stage)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each stage's rows are written to the shared folder and read again."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs, _ = written(stage(spark, docs, sf_dir), name)
    return docs

"""The queries of this subpackage, each over its whole table with production parameters."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontaminate, langid, mixing, neardup, pii, quality, secrets, sharding, substring, tokenfile
from .common import table
from .oracles import ORACLES  # noqa: F401

SHARDS = [f"shard-{i:03d}" for i in range(16)]


def mixing_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents"))


def decontamination_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.search(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def sharding_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "source")
    return sharding.assign(docs, "doc_id", SHARDS).select("doc_id", "source", "slot", "shard")


def substring_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring.dedup(table(spark, sf_dir, "documents"))


def pii_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.detect(table(spark, sf_dir, "documents"))


def secrets_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The table in two commits, rows of even ids and the rest; of each, unseen blobs are scanned."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    even = (F.col("doc_id") % 2).eqNullSafe(0)
    return secrets.history([docs.filter(even), docs.filter(~even)], docs, secrets.new_ledger(spark))


def token_file_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokenfile.round_trip(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def language_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return langid.identify(docs, langid.training_sample(docs))


def near_dedup_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.group(table(spark, sf_dir, "documents"))


def quality_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ledger is written once; both policy versions are applied to it."""
    led = quality.recorded(table(spark, sf_dir, "documents"))
    base = quality.apply_policy(led, quality.POLICIES["v1"]).withColumnRenamed("kept", "kept_v1")
    return quality.apply_policy(base).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "kept_v1", "fail_bits")


def quality_ablation_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.ablation(quality.recorded(table(spark, sf_dir, "documents")))


QUERIES = {
    "op1_mixing": mixing_query,
    "op2_sharding": sharding_query,
    "op3_substring": substring_query,
    "op4_pii": pii_query,
    "op5_secrets": secrets_query,
    "op6_decontamination": decontamination_query,
    "op7_token_file": token_file_query,
    "op8_near_dedup": near_dedup_query,
    "op9_language": language_query,
    "op10_quality": quality_query,
    "quality_ablation": quality_ablation_query,
}

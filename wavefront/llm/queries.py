"""The queries that __spark_entry__ adds for this subpackage: each applies one operator to its whole table."""

from __future__ import annotations

import os
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from wavefront.llm import bpe, embeddings, licences, media, minhash, mixing, oracles, sharding, suffix_dedup, toxicity, urls


def tokenizer_path() -> str:
    """The vocabulary file; set WAVEFRONT_TOKENIZER to use another."""
    if found := os.environ.get("WAVEFRONT_TOKENIZER"):
        return found
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def _documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def op1_feistel_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard(_documents(spark, sf_dir))


def op2_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_documents(_documents(spark, sf_dir), tokenizer_path()).drop("ids")


def op3_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.as_media(_documents(spark, sf_dir)).drop("key_ranges", "media")


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.grade_documents(_documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op5_licences(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licences.scan(_documents(spark, sf_dir))


def op6_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.remove_repeats(_documents(spark, sf_dir), keep=False).drop("kept")


def op7_minhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(_documents(spark, sf_dir))


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(_documents(spark, sf_dir))


def op9_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embeddings.near_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))


def op10_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urls.judge(spark.read.parquet(f"{sf_dir}/pages.parquet"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_feistel_shards": op1_feistel_shards,
    "op2_bpe": op2_bpe,
    "op3_media": op3_media,
    "op4_toxicity": op4_toxicity,
    "op5_licences": op5_licences,
    "op6_suffix_dedup": op6_suffix_dedup,
    "op7_minhash_dedup": op7_minhash_dedup,
    "op8_mixing": op8_mixing,
    "op9_embedding_dedup": op9_embedding_dedup,
    "op10_url_filter": op10_url_filter,
}
#: The other operators hash, encode or learn, which plain SQL cannot; tests/llm holds them against brute force.
ORACLE: dict[str, str] = {
    "op5_licences": oracles.licences(),
    "op7_minhash_dedup": oracles.NEAR_DUPLICATES,
    "op9_embedding_dedup": oracles.NEAR_VECTORS,
}

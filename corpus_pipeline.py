"""A training corpus from ``documents``: toxic rows out, one of each near-duplicate group, repeated passages cut, sources
mixed to their targets in training order, texts encoded. Each stage takes the whole output of the one before."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from wavefront.llm import bpe, minhash, mixing, suffix_dedup, toxicity
from wavefront.llm.queries import tokenizer_path
from wavefront.session import cut


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose expected severity reaches the threshold go; null and empty texts, null and repeated ids, ties and extra columns stay as they are."""
    return toxicity.drop_toxic(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of near-duplicates (80 in 100 of five-word shingles) the least id stays; wordless rows and rows without an id all stay."""
    return minhash.one_of_each(docs)


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of 400 bytes or 51 words that start twice or more are cut from the texts; no row goes, a null text stays null, one that repeats throughout becomes empty."""
    return suffix_dedup.without_repeats(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows as often as the mix takes them, in training order; wordless rows carry no demand and are not taken, equal rows share what their numbers take."""
    return mixing.training_order(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Tokens of every whole text, a row for each input row; a null text has none."""
    return bpe.encode_documents(docs, tokenizer_path())


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("suffix_dedup", cut_repeats),
    ("mixing", mix_sources),
    ("bpe", encode),
]

#: Learned and iterative stages have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs if k == 0 else cut(docs), sf_dir)
    return docs

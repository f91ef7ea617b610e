"""Corpus pipeline: reject low quality, keep one of each near-duplicate class, drop benchmark leaks, mask secrets, encode.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame; it is written as Parquet to shared storage and read
again as the next stage's docs.  All stages but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from momenttree.llm import bpe, decontaminate, quality, secrets, simhash
from momenttree.llm.queries import table
from momenttree.llm.runtime import stored


def accept_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the factorisation machine accepts."""
    return quality.keep_good(docs, table(spark, sf_dir, "labels"))


def keep_one_of_near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of the smallest id of each SimHash class."""
    return simhash.keep_one(docs)


def drop_benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item."""
    return decontaminate.drop_leaks(docs, table(spark, sf_dir, "benchmark"))


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, live-looking credentials masked."""
    return secrets.redact(docs)


def encode_texts(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens and digests of ids and decoded text."""
    return bpe.digests(docs)


STAGES = [
    ("quality classifier", accept_quality),
    ("simhash near-dedup", keep_one_of_near),
    ("benchmark decontamination", drop_benchmark_leaks),
    ("secret scans", mask_secrets),
    ("bpe encoding and decoding", encode_texts),
]
#: The first stage is a trained model; tests compare the run with a brute-force version instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stored(stage(spark, docs, sf_dir), f"stage{k}")
    return docs

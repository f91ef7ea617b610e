"""Labelled samples: which rows may teach, and a bounded, repeatable choice among them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def fold(modulus: int, doc_id: str = "doc_id") -> Column:
    """crc32 of the id as text, modulo; a null id counts as the empty text."""
    return F.crc32(F.coalesce(F.col(doc_id).cast("string"), F.lit("")).cast("binary")) % modulus


def sample(docs: DataFrame, labels: DataFrame, label: str, teaches: Column, bound: int) -> DataFrame:
    """doc_id, text, n_chars (null where docs has none) and y of at most `bound` labelled ids that may teach.

    The ids with the smallest hashes are taken, so the choice does not depend on partitions; null labels and ids
    teach nothing, an id with several labels has the largest, and of rows with one id the smallest text teaches.  The id
    list is bounded, hence broadcast.
    """
    known = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull()).where(teaches).groupBy("doc_id").agg(F.max(label).cast("int").alias("y"))
    chosen = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(bound)
    n_chars = F.col("n_chars").cast("double") if "n_chars" in docs.columns else F.lit(None).cast("double")
    rows = docs.select("doc_id", F.col("text").cast("string").alias("text"), n_chars.alias("n_chars")).join(F.broadcast(chosen), "doc_id")
    return rows.groupBy("doc_id").agg(F.min(F.struct("text", "n_chars")).alias("r"), F.first("y").alias("y")).select("doc_id", "r.text", "r.n_chars", "y")

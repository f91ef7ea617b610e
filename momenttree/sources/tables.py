"""The given tables and the corpora made of them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from momenttree.functions.text import page_title, sentences, strip_markup

SCHEMAS = {
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "labels": "doc_id bigint, quality int, toxic int",
    "pages": "page_id bigint, url string, html string",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
    "benchmark": "item_id bigint, text string",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
}


def read_table(spark: SparkSession, directory: str, name: str) -> DataFrame:
    """One table; the schema comes from the files, whose footers Spark reads anyway."""
    return spark.read.parquet(f"{directory}/{name}.parquet")


def titles(spark: SparkSession, directory: str) -> DataFrame:
    """Short texts: the first sentence of each document."""
    first = F.coalesce(F.try_element_at(sentences(F.col("text")), F.lit(1)), F.lit(""))
    return read_table(spark, directory, "documents").select("doc_id", first.alias("text"))


def page_titles(spark: SparkSession, directory: str) -> DataFrame:
    return read_table(spark, directory, "pages").select(F.col("page_id").alias("doc_id"), page_title(F.col("html")).alias("text"))


def pages_text(spark: SparkSession, directory: str) -> DataFrame:
    """Long texts: pages without their markup."""
    return read_table(spark, directory, "pages").select(F.col("page_id").alias("doc_id"), strip_markup(F.col("html")).alias("text"), page_title(F.col("html")).alias("title"))


def conversation_docs(spark: SparkSession, directory: str) -> DataFrame:
    """A document for each conversation, its turns in order; turns of one conversation are few."""
    turns = F.array_sort(F.collect_list(F.struct("turn", "text")))
    return read_table(spark, directory, "conversations").groupBy("conv_id").agg(turns.alias("turns")).select(F.col("conv_id").alias("doc_id"), F.array_join(F.col("turns.text"), "\n").alias("text"), F.size("turns").alias("n_turns"))


def baskets(spark: SparkSession, directory: str, column: str = "p_brand") -> DataFrame:
    """Orders as documents whose words are the brands (or types) of their parts: doc_id, words."""
    items = read_table(spark, directory, "lineitem").select("l_orderkey", "l_partkey").join(read_table(spark, directory, "part").select("p_partkey", column), F.col("l_partkey") == F.col("p_partkey"))
    return items.groupBy(F.col("l_orderkey").alias("doc_id")).agg(F.array_sort(F.collect_list(column)).alias("words"))


def user_docs(spark: SparkSession, directory: str) -> DataFrame:
    """Users as documents whose words are event types with a bucket of their property k: doc_id, words."""
    bucket = F.floor(F.get_json_object("props", "$.k").cast("int") / 10)
    word = F.concat_ws("_", "event_type", bucket.cast("string"))
    return read_table(spark, directory, "events").groupBy(F.col("user_id").alias("doc_id")).agg(F.array_sort(F.collect_list(word)).alias("words"))


def nation_docs(spark: SparkSession, directory: str) -> DataFrame:
    """Nations as documents whose words are the balances of their suppliers in steps of 500: doc_id, words."""
    word = F.concat(F.lit("b"), F.floor(F.col("s_acctbal") / 500).cast("string"))
    rows = read_table(spark, directory, "supplier").where("s_nationkey is not null and s_acctbal is not null")
    return rows.groupBy(F.col("s_nationkey").cast("bigint").alias("doc_id")).agg(F.array_sort(F.collect_list(word)).alias("words"))

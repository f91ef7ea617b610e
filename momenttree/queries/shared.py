"""What several queries start from, in both dialects."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from momenttree.operators import corpus as C
from momenttree.runtime import spread
from momenttree.sources.tables import read_table

WORDS = r"regexp_extract_all(lower(coalesce(text, '')), '\p{L}+')"
TOK = f"tok AS (SELECT doc_id, lang, unnest({WORDS}) AS term FROM documents)"
CNT = "cnt AS (SELECT doc_id, lang, term, count(*) AS c FROM tok GROUP BY ALL)"


def vocab_sql(top: int | None = None, min_df: int = 1) -> str:
    limit = f" QUALIFY row_number() OVER (ORDER BY count(*) DESC, term) <= {top}" if top else ""
    return f"vocab AS (SELECT term, CAST(row_number() OVER (ORDER BY count(*) DESC, term) - 1 AS INT) AS term_id, count(*) AS df, CAST(sum(c) AS BIGINT) AS tf FROM cnt GROUP BY term HAVING count(*) >= {min_df}{limit})"


def bags_sql(top: int | None = None, min_df: int = 1) -> str:
    """CTEs tok, cnt, vocab, lb, len, kept (doc_id, lang, term_id, c, l) and d (number of kept documents)."""
    return f"{TOK}, {CNT}, {vocab_sql(top, min_df)}, lb AS (SELECT doc_id, lang, term_id, c FROM cnt JOIN vocab USING (term)), len AS (SELECT doc_id, sum(c) AS l FROM lb GROUP BY doc_id HAVING sum(c) >= 3), kept AS (SELECT lb.*, CAST(l AS DOUBLE) AS l FROM lb JOIN len USING (doc_id)), d AS (SELECT CAST(count(*) AS DOUBLE) AS d FROM len)"


#: The languages as known topics: path, alpha; words of each by their share.
LANG_SQL = "langs AS (SELECT lang, 'o/' || CAST(row_number() OVER (ORDER BY lang) AS VARCHAR) AS path, count(*) * 1.0 / (SELECT count(*) FROM documents WHERE lang IS NOT NULL) AS alpha FROM documents WHERE lang IS NOT NULL GROUP BY lang), phi AS (SELECT path, term_id, CAST(sum(c) AS DOUBLE) / sum(sum(c)) OVER (PARTITION BY path) AS phi FROM lb JOIN langs USING (lang) GROUP BY path, term_id), omega AS (SELECT path, term_id, alpha * phi / sum(alpha * phi) OVER (PARTITION BY term_id) AS omega FROM phi JOIN langs USING (path))"


def r6(c: Column | str, scale: float = 1.0) -> Column:
    """Rounded to 6 places after scaling, never minus zero."""
    c = F.col(c) if isinstance(c, str) else c
    return F.round(c * scale, 6) + F.lit(0.0)


def r6_sql(c: str, scale: float = 1.0) -> str:
    return f"round(({c}) * {scale}, 6) + 0.0"


def documents(spark: SparkSession, sf: str) -> DataFrame:
    return spread(read_table(spark, sf, "documents"))


def tokens(spark: SparkSession, sf: str) -> DataFrame:
    return C.tokens(documents(spark, sf))


def prepared(spark: SparkSession, sf: str, top: int | None = None, min_df: int = 1) -> tuple[DataFrame, DataFrame, int]:
    """Vocabulary (cached, bounded by top), bags and the vocabulary's size."""
    tok = tokens(spark, sf)
    vocab = C.vocabulary(tok, top=top, min_df=min_df).cache()
    v = vocab.count()
    return vocab, C.bags(tok, vocab, size=v), v


def long_prepared(spark: SparkSession, sf: str, top: int | None = None) -> tuple[DataFrame, DataFrame]:
    """Vocabulary and (doc_id, term_id, c)."""
    tok = tokens(spark, sf)
    vocab = C.vocabulary(tok, top=top).cache()
    return vocab, C.long_bags(tok, vocab, vocab.count())


def lang_topics(spark: SparkSession, sf: str, top: int) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """vocabulary, (doc_id, term_id, c), nodes (path, parent, lang, alpha), words (path, term_id, phi): languages as known topics."""
    vocab, long = long_prepared(spark, sf, top)
    docs = documents(spark, sf).where("lang is not null").select("doc_id", "lang")
    sizes = docs.groupBy("lang").agg(F.count("*").alias("n"))
    total = F.sum("n").over(Window.partitionBy())  # a row for each language
    nodes = sizes.select(F.concat(F.lit("o/"), F.row_number().over(Window.orderBy("lang")).cast("string")).alias("path"), F.lit("o").alias("parent"), "lang", (F.col("n") / total).alias("alpha"))
    counted = long.join(docs, "doc_id").groupBy("lang", "term_id").agg(F.sum("c").alias("c")).join(F.broadcast(nodes), "lang")
    words = counted.select("path", "term_id", (F.col("c") / F.sum("c").over(Window.partitionBy("path"))).alias("phi"))
    return vocab, long, nodes, words


def lang_weights(nodes: DataFrame, words: DataFrame) -> DataFrame:
    """path, term_id, omega: posterior of the language given the word."""
    joint = words.join(F.broadcast(nodes.select("path", "alpha")), "path").withColumn("j", F.col("alpha") * F.col("phi"))
    return joint.select("path", "term_id", (F.col("j") / F.sum("j").over(Window.partitionBy("term_id"))).alias("omega"))

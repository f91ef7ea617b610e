"""Streams over events, run to their end; their twins are batch SQL over the same rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from momenttree.queries import query
from momenttree.runtime import stored
from momenttree.sources.tables import read_table
from momenttree.streaming import moments as S

_WORD = "event_type || '_' || CAST(floor(CAST(json_extract_string(props, '$.k') AS INT) / 10.0) AS BIGINT)"


def _words(spark: SparkSession, sf: str) -> DataFrame:
    return S.word_of(S.event_stream(spark, sf))


@query(f"SELECT time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01') AS start, {_WORD} AS word, count(*) AS n FROM events GROUP BY ALL")
def stream_tumbling(spark: SparkSession, sf: str) -> DataFrame:
    return S.run_to_table(S.tumbling_numerators(_words(spark, sf)), "tumbling", "complete")


@query("SELECT time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '1970-01-01') - INTERVAL 12 HOUR * k AS start, count(*) AS n FROM events CROSS JOIN (VALUES (0), (1)) t(k) GROUP BY ALL")
def stream_sliding(spark: SparkSession, sf: str) -> DataFrame:
    return S.run_to_table(S.sliding_counts(_words(spark, sf)), "sliding", "complete")


@query("WITH a AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 2 HOUR THEN 1 ELSE 0 END AS new FROM events), b AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM a) SELECT user_id, min(ts) AS start, count(*) AS n FROM b GROUP BY user_id, s")
def stream_sessions(spark: SparkSession, sf: str) -> DataFrame:
    return S.run_to_table(S.session_docs(_words(spark, sf)), "sessions", "complete")


@query("WITH a AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 2 HOUR THEN 1 ELSE 0 END AS new FROM events), b AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM a) SELECT user_id, min(ts) AS start, count(*) AS n FROM b GROUP BY user_id, s")
def batch_sessions(spark: SparkSession, sf: str) -> DataFrame:
    return S.session_docs(S.word_of(read_table(spark, sf, "events")))


@query("SELECT count(*) AS n, count(DISTINCT event_id) AS n_events FROM events")
def stream_dedupe(spark: SparkSession, sf: str) -> DataFrame:
    """Every event comes twice; the copies go."""
    words = _words(spark, sf)
    twice = words.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2)))).drop("copy")
    return S.run_to_table(S.deduplicated(twice), "dedupe", "append", lambda t: t.agg(F.count("*").alias("n"), F.countDistinct("event_id").alias("n_events")))


@query(f"WITH o AS (SELECT user_id, {_WORD} AS word, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1 AS k FROM events) SELECT user_id, CAST(k // 20 AS INT) AS part, word, count(*) AS n FROM o GROUP BY ALL")
def stream_stateful_bags(spark: SparkSession, sf: str) -> DataFrame:
    """All events of every user, the last bag shorter than the others."""
    flat = lambda t: S.latest_bags(t).select("user_id", "part", F.explode(F.arrays_zip("words", "counts")).alias("x")).select("user_id", "part", F.col("x.words").alias("word"), F.col("x.counts").alias("n"))
    return S.run_to_table(S.stateful_bags(_words(spark, sf), every=20), "bags", "append", flat)


@query(f"WITH w AS (SELECT user_id, {_WORD} AS word, event_type FROM events), t AS (SELECT word, count(*) AS n FROM w GROUP BY word) SELECT event_id, round(1.0 / n, 9) AS weight FROM (SELECT event_id, {_WORD} AS word FROM events) JOIN t USING (word)")
def stream_static_join(spark: SparkSession, sf: str) -> DataFrame:
    """Events weighted on the fly by a fixed table of word weights."""
    static = S.word_of(read_table(spark, sf, "events")).groupBy("word").agg((1.0 / F.count("*")).alias("weight"))
    # a row for each word of a fixed vocabulary of event types and buckets: bounded
    return S.run_to_table(_words(spark, sf).join(F.broadcast(stored(static, "static")), "word").select("event_id", F.round("weight", 9).alias("weight")), "joined")

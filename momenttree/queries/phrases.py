"""Phrase mining, quality, topical counts and ranking, languages as known topics."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from momenttree.operators import phrases as P
from momenttree.queries import query
from momenttree.queries.corpus import SENT
from momenttree.queries.shared import documents, r6, r6_sql
from momenttree.runtime import cut

SUPPORT = 40
#: Length that the SQL twins reach; the queries named ..._whole have no cap and no twin.
MOST = 3

_GRAMS = " UNION ALL ".join(f"SELECT doc_id, array_to_string(list_slice(words, i, i + {n - 1}), ' ') AS phrase, {n} AS n FROM (SELECT doc_id, words, unnest(range(1, len(words) - {n - 2})) AS i FROM sent WHERE len(words) >= {n})" for n in range(1, MOST + 1))
MINED = f"{SENT}, grams AS ({_GRAMS}), phr AS (SELECT phrase, n, count(*) AS support FROM grams GROUP BY ALL HAVING count(*) >= {SUPPORT})"


def _mined(spark: SparkSession, sf: str, most: int | None = MOST, tag: Column | None = None) -> P.Mined:
    return P.mine(P.by_document(documents(spark, sf), tag), SUPPORT, most)


def _frequent(spark: SparkSession, sf: str, most: int | None = MOST) -> DataFrame:
    return _mined(spark, sf, most).phrases.select("phrase", "n", "support")


@query(f"WITH {MINED} SELECT phrase, n, support FROM phr")
def frequent_phrases(spark: SparkSession, sf: str) -> DataFrame:
    return _frequent(spark, sf)


@query()
def frequent_phrases_whole(spark: SparkSession, sf: str) -> DataFrame:
    """Phrases of any length."""
    return _frequent(spark, sf, None)


_RATIO = "longer AS (SELECT unnest([regexp_replace(phrase, ' [^ ]*$', ''), regexp_replace(phrase, '^[^ ]* ', '')]) AS phrase, support AS s FROM phr WHERE n > 1), ratios AS (SELECT p.phrase, n, support, coalesce(max(s), 0) * 1.0 / support AS ratio FROM phr p LEFT JOIN longer l ON l.phrase = p.phrase GROUP BY p.phrase, n, support)"


@query(f"WITH {MINED}, {_RATIO} SELECT phrase, {r6_sql('ratio')} AS ratio FROM ratios WHERE ratio < 0.9")
def complete_phrases(spark: SparkSession, sf: str) -> DataFrame:
    return _complete(_mined(spark, sf))


@query()
def complete_phrases_whole(spark: SparkSession, sf: str) -> DataFrame:
    return _complete(_mined(spark, sf, None))


def _complete(mined: P.Mined) -> DataFrame:
    measured = P.complete_ratio(mined.phrases).where("ratio < 0.9") if mined.codes is None else mined.where("ratio < 0.9")
    return measured.select("phrase", r6("ratio").alias("ratio"))


@query(f"WITH {MINED}, total AS (SELECT CAST(sum(len(words)) AS DOUBLE) AS t FROM sent), w AS (SELECT phrase, n, support, string_split(phrase, ' ') AS parts FROM phr WHERE n > 1), s AS (SELECT phrase, support, array_to_string(list_slice(parts, 1, k), ' ') AS a, array_to_string(list_slice(parts, k + 1, n), ' ') AS b FROM (SELECT *, unnest(range(1, n)) AS k FROM w)) SELECT s.phrase, {r6_sql('min((s.support - x.support * y.support / t) / sqrt(s.support))')} AS z FROM s JOIN phr x ON x.phrase = a JOIN phr y ON y.phrase = b CROSS JOIN total GROUP BY s.phrase")
def phraseness(spark: SparkSession, sf: str) -> DataFrame:
    return _phraseness(_mined(spark, sf))


@query()
def phraseness_whole(spark: SparkSession, sf: str) -> DataFrame:
    return _phraseness(_mined(spark, sf, None))


def _phraseness(mined: P.Mined) -> DataFrame:
    measured = P.phraseness(mined.phrases, P.n_tokens_of(mined.by_doc)) if mined.codes is None else mined.where("n > 1")
    return measured.select("phrase", r6("z").alias("z"))


_COUNTS = "counts AS (SELECT doc_id, phrase, count(*) AS c FROM grams JOIN phr USING (phrase) GROUP BY ALL)"


@query(f"WITH {MINED}, {_COUNTS} SELECT doc_id, phrase, c FROM counts")
def phrase_counts(spark: SparkSession, sf: str) -> DataFrame:
    return P.counts_in_place(_mined(spark, sf))


@query()
def phrase_counts_whole(spark: SparkSession, sf: str) -> DataFrame:
    return P.counts_in_place(_mined(spark, sf, None))


#: Topics: languages; words: the frequent single words by their share in each.
_TOPICS = "nd AS (SELECT lang, 'o/' || CAST(row_number() OVER (ORDER BY lang) AS VARCHAR) AS path, count(*) * 1.0 / (SELECT count(*) FROM documents WHERE lang IS NOT NULL) AS alpha FROM documents WHERE lang IS NOT NULL GROUP BY lang), wd AS (SELECT path, phrase AS term, CAST(sum(c) AS DOUBLE) / sum(sum(c)) OVER (PARTITION BY path) AS phi FROM counts JOIN phr USING (phrase) JOIN documents USING (doc_id) JOIN nd USING (lang) WHERE n = 1 GROUP BY path, phrase)"
_POST = "pw AS (SELECT phrase, n, unnest(string_split(phrase, ' ')) AS term FROM phr), lp AS (SELECT phrase, path, sum(ln(phi)) + ln(any_value(alpha)) AS lp FROM pw JOIN wd USING (term) JOIN nd USING (path) GROUP BY phrase, path, n HAVING count(*) = n), post AS (SELECT phrase, path, exp(lp - m) / sum(exp(lp - m)) OVER (PARTITION BY phrase) AS share FROM (SELECT *, max(lp) OVER (PARTITION BY phrase) AS m FROM lp))"
_TOPICAL = "tc AS (SELECT doc_id, 'o' AS path, phrase, CAST(c AS DOUBLE) AS c FROM counts UNION ALL SELECT doc_id, path, phrase, c * share FROM counts JOIN post USING (phrase))"
_PROB = "tt AS (SELECT doc_id, path, sum(c) AS total FROM tc GROUP BY ALL HAVING sum(c) > 0), pr AS (SELECT path, phrase, sum(c / total) / (SELECT count(*) FROM documents) AS p FROM tc JOIN tt USING (doc_id, path) GROUP BY ALL)"
_BASE = f"{MINED}, {_COUNTS}, {_TOPICS}, {_POST}, {_TOPICAL}, {_PROB}"


#: Two levels of a known tree: languages, and in each its short (0) and its long (1) documents.
LONG_TEXT = 1_000


def _tag() -> Column:
    """0 or 1, then the language; null without one."""
    return F.concat((F.coalesce("n_chars", F.lit(0)) >= LONG_TEXT).cast("int").cast("string"), F.col("lang"))


def _words(mined: P.Mined, tags: DataFrame) -> DataFrame:
    """path, term, phi: the frequent single words by their share in each node; tags (tag, path): a row for each tag and node of its documents."""
    summed = P.words_by_tag(mined).join(F.broadcast(tags), "tag").groupBy("path", "term").agg(F.sum("c").alias("c"))
    return cut(summed.select("path", "term", (F.col("c") / F.sum("c").over(Window.partitionBy("path"))).alias("phi")))


def _topics(spark: SparkSession, sf: str, whole: bool = False) -> tuple[P.Mined, DataFrame, DataFrame, DataFrame]:
    """mined phrases, phrases, nodes, words (all cut or stored: each is used several times).

    whole: phrases of any length, of these the complete and significant ones; words are of all frequent single words still.
    """
    mined = _mined(spark, sf, None if whole else MOST, _tag())
    phrases = cut(P.good_of(mined)) if whole else mined.phrases
    docs = documents(spark, sf).where("lang is not null").select("doc_id", "lang")
    sizes = docs.groupBy("lang").agg(F.count("*").alias("n"))
    nodes = cut(sizes.select(F.concat(F.lit("o/"), F.row_number().over(Window.orderBy("lang")).cast("string")).alias("path"), F.lit("o").alias("parent"), "lang", (F.col("n") / F.sum("n").over(Window.partitionBy())).alias("alpha")))
    tags = nodes.select(F.explode(F.array(*(F.concat(F.lit(x), "lang") for x in "01"))).alias("tag"), "path")
    return mined, phrases, nodes, _words(mined, tags)


def _topical(spark: SparkSession, sf: str, whole: bool = False) -> DataFrame:
    mined, phrases, nodes, words = _topics(spark, sf, whole)
    return P.topical_phrase_counts(P.counts_in_place(mined, phrases), cut(P.phrase_posterior(phrases, words, nodes)))


def _probability(spark: SparkSession, sf: str, whole: bool = False) -> DataFrame:
    mined, phrases, nodes, words = _topics(spark, sf, whole)
    return cut(P.probability_in_place(mined, phrases, P.phrase_posterior(phrases, words, nodes), documents(spark, sf).count()))


@query(f"WITH {_BASE} SELECT doc_id, path, phrase, {r6_sql('c')} AS c FROM tc")
def topical_phrase_counts(spark: SparkSession, sf: str) -> DataFrame:
    return _topical(spark, sf).select("doc_id", "path", "phrase", r6("c").alias("c"))


@query(f"WITH {_BASE} SELECT path, phrase, {r6_sql('p', 1e4)} AS p FROM pr")
def phrase_probability(spark: SparkSession, sf: str) -> DataFrame:
    return _probability(spark, sf).select("path", "phrase", r6("p", 1e4).alias("p"))


def _ranked_sql(score: str) -> str:
    return f"WITH {_BASE}, sc AS (SELECT a.path, a.phrase, a.p AS p_topic, b.p AS p_parent, {score} AS score FROM pr a JOIN pr b ON b.path = 'o' AND a.phrase = b.phrase WHERE a.path <> 'o'), rk AS (SELECT *, CAST(row_number() OVER (PARTITION BY path ORDER BY round(score, 12) DESC, phrase) AS INT) AS rank FROM sc)"


_SELECT = f"SELECT path, rank, phrase, {r6_sql('p_topic', 1e4)} AS p_topic, {r6_sql('p_parent', 1e4)} AS p_parent, {r6_sql('score', 1e4)} AS score FROM rk WHERE rank <= 20"


def _ranked(spark: SparkSession, sf: str, by: str, whole: bool = False) -> DataFrame:
    ranked = P.rank_phrases(_probability(spark, sf, whole), 20, by)
    return ranked.select("path", "rank", "phrase", r6("p_topic", 1e4).alias("p_topic"), r6("p_parent", 1e4).alias("p_parent"), r6("score", 1e4).alias("score"))


@query(f"{_ranked_sql('a.p * ln(a.p / b.p)')} {_SELECT}")
def phrase_ranking(spark: SparkSession, sf: str) -> DataFrame:
    return _ranked(spark, sf, "both")


@query(f"{_ranked_sql('a.p')} {_SELECT}")
def phrase_ranking_popularity(spark: SparkSession, sf: str) -> DataFrame:
    return _ranked(spark, sf, "popularity")


@query(f"{_ranked_sql('ln(a.p / b.p)')} {_SELECT}")
def phrase_ranking_ratio(spark: SparkSession, sf: str) -> DataFrame:
    return _ranked(spark, sf, "ratio")


@query(f"{_ranked_sql('a.p * ln(a.p / b.p)')}, pl AS (SELECT *, row_number() OVER (PARTITION BY path, regexp_replace(phrase, 's$', '') ORDER BY rank) AS k FROM rk) SELECT path, CAST(row_number() OVER (PARTITION BY path ORDER BY rank) AS INT) AS rank, phrase FROM pl WHERE k = 1")
def plural_collapsed(spark: SparkSession, sf: str) -> DataFrame:
    return P.collapse_plurals(P.rank_phrases(_probability(spark, sf))).select("path", "rank", "phrase")


@query()
def topical_phrase_counts_whole(spark: SparkSession, sf: str) -> DataFrame:
    return _topical(spark, sf, True).select("doc_id", "path", "phrase", r6("c").alias("c"))


@query()
def phrase_probability_whole(spark: SparkSession, sf: str) -> DataFrame:
    return _probability(spark, sf, True).select("path", "phrase", r6("p", 1e4).alias("p"))


@query()
def phrase_ranking_whole(spark: SparkSession, sf: str) -> DataFrame:
    return _ranked(spark, sf, "both", True)


@query()
def phrase_ranking_popularity_whole(spark: SparkSession, sf: str) -> DataFrame:
    return _ranked(spark, sf, "popularity", True)


@query()
def phrase_ranking_ratio_whole(spark: SparkSession, sf: str) -> DataFrame:
    return _ranked(spark, sf, "ratio", True)


@query()
def plural_collapsed_whole(spark: SparkSession, sf: str) -> DataFrame:
    return P.collapse_plurals(P.rank_phrases(_probability(spark, sf, True))).select("path", "rank", "phrase")


_Z = f"total AS (SELECT CAST(sum(len(words)) AS DOUBLE) AS t FROM sent), zs AS (SELECT s.phrase, min((s.support - x.support * y.support / t) / sqrt(s.support)) AS z FROM (SELECT phrase, support, array_to_string(list_slice(parts, 1, k), ' ') AS a, array_to_string(list_slice(parts, k + 1, n), ' ') AS b FROM (SELECT *, unnest(range(1, n)) AS k FROM (SELECT phrase, n, support, string_split(phrase, ' ') AS parts FROM phr WHERE n > 1))) s JOIN phr x ON x.phrase = a JOIN phr y ON y.phrase = b CROSS JOIN total GROUP BY s.phrase)"
_GOOD = f"{_Z}, {_RATIO}, good AS (SELECT phrase, n FROM ratios LEFT JOIN zs USING (phrase) WHERE ratio < 0.9 AND (n = 1 OR z >= {P.SIGNIFICANT}))"
_DEEP = f"{MINED}, {_GOOD}, dn AS (SELECT doc_id, l1, l1 || '/' || CASE WHEN coalesce(n_chars, 0) >= {LONG_TEXT} THEN '2' ELSE '1' END AS l2 FROM (SELECT doc_id, n_chars, 'o/' || CAST(dense_rank() OVER (ORDER BY lang) AS VARCHAR) AS l1 FROM documents WHERE lang IS NOT NULL)), nd AS (SELECT l1 AS path, 'o' AS parent, count(*) * 1.0 / (SELECT count(*) FROM dn) AS alpha FROM dn GROUP BY 1 UNION ALL SELECT l2, l1, count(*) * 1.0 / (SELECT count(*) FROM dn) FROM dn GROUP BY 1, 2), c1 AS (SELECT doc_id, phrase AS term, count(*) AS c FROM grams JOIN phr USING (phrase) WHERE phr.n = 1 GROUP BY ALL), wd AS (SELECT path, term, CAST(sum(c) AS DOUBLE) / sum(sum(c)) OVER (PARTITION BY path) AS phi FROM (SELECT l1 AS path, term, c FROM c1 JOIN dn USING (doc_id) UNION ALL SELECT l2, term, c FROM c1 JOIN dn USING (doc_id)) GROUP BY path, term), counts AS (SELECT doc_id, phrase, count(*) AS c FROM grams JOIN good USING (phrase) GROUP BY ALL), lp AS (SELECT phrase, path, parent, sum(ln(phi)) + ln(any_value(alpha)) AS lp FROM (SELECT phrase, n, unnest(string_split(phrase, ' ')) AS term FROM good) JOIN wd USING (term) JOIN nd USING (path) GROUP BY phrase, path, parent, n HAVING count(*) = n), post AS (SELECT phrase, path, parent, exp(lp - m) / sum(exp(lp - m)) OVER (PARTITION BY phrase, parent) AS share FROM (SELECT *, max(lp) OVER (PARTITION BY phrase, parent) AS m FROM lp)), sh AS (SELECT phrase, path, share FROM post WHERE parent = 'o' UNION ALL SELECT b.phrase, b.path, b.share * a.share FROM post b JOIN post a ON a.phrase = b.phrase AND a.path = b.parent), {_TOPICAL.replace('JOIN post', 'JOIN sh')}, {_PROB}"


def _deep_tree(spark: SparkSession, sf: str, mined: P.Mined) -> tuple[DataFrame, DataFrame]:
    """nodes (path, parent, alpha) and words (path, term, phi) of the known tree of two levels."""
    docs = documents(spark, sf).where("lang is not null").select("doc_id", "lang", (F.coalesce("n_chars", F.lit(0)) >= LONG_TEXT).alias("long"))
    numbers = docs.select("lang").distinct().select("lang", F.row_number().over(Window.orderBy("lang")).cast("string").alias("k"))  # a row for each language
    first = F.concat(F.lit("o/"), "k")
    member = cut(docs.join(F.broadcast(numbers), "lang").select("doc_id", first.alias("l1"), F.concat(first, F.when(F.col("long"), "/2").otherwise("/1")).alias("l2")))
    each = member.select("doc_id", F.explode(F.array(F.struct(F.col("l1").alias("path"), F.lit("o").alias("parent")), F.struct(F.col("l2").alias("path"), F.col("l1").alias("parent")))).alias("n")).select("doc_id", "n.*")
    nodes = cut(each.groupBy("path", "parent").agg((F.count("*") / member.count()).alias("alpha")))
    tags = numbers.select(F.explode(F.array(*(F.struct(F.concat(F.lit(x), "lang").alias("tag"), path.alias("path")) for x in "01" for path in (first, F.concat(first, F.lit(f"/{int(x) + 1}")))))).alias("t")).select("t.*")
    return nodes, _words(mined, tags)


def _hierarchy(spark: SparkSession, sf: str, most: int | None) -> DataFrame:
    mined = _mined(spark, sf, most, _tag())
    nodes, words = _deep_tree(spark, sf, mined)
    ranked = P.rank_tree(mined, nodes, words, documents(spark, sf).count(), top=20)
    return ranked.select("path", "rank", "phrase", r6("p_topic", 1e4).alias("p_topic"), r6("p_parent", 1e4).alias("p_parent"), r6("score", 1e4).alias("score"))


@query(f"WITH {_DEEP}, sc AS (SELECT a.path, a.phrase, a.p AS p_topic, b.p AS p_parent, a.p * ln(a.p / b.p) AS score FROM pr a JOIN pr b ON b.path = regexp_replace(a.path, '/[^/]*$', '') AND a.phrase = b.phrase WHERE a.path <> 'o'), rk AS (SELECT *, CAST(row_number() OVER (PARTITION BY path ORDER BY round(score, 12) DESC, phrase) AS INT) AS rank FROM sc) {_SELECT}")
def phrase_hierarchy(spark: SparkSession, sf: str) -> DataFrame:
    """Complete and significant phrases ranked under both levels of a known tree."""
    return _hierarchy(spark, sf, MOST)


@query()
def phrase_hierarchy_whole(spark: SparkSession, sf: str) -> DataFrame:
    return _hierarchy(spark, sf, None)

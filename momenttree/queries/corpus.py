"""Corpus preparation and its twins."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from momenttree.functions import text as T
from momenttree.operators import corpus as C
from momenttree.queries import query
from momenttree.queries.shared import CNT, TOK, WORDS, bags_sql, documents, long_prepared, prepared, r6, tokens, vocab_sql
from momenttree.runtime import shared_dir
from momenttree.sources import tables


def _list(words: list[str]) -> str:
    return "[" + ", ".join("'" + w.replace("'", "''") + "'" for w in words) + "]"


@query("SELECT doc_id, lang, n_chars FROM documents")
def scan_documents(spark: SparkSession, sf: str) -> DataFrame:
    return documents(spark, sf).select("doc_id", "lang", "n_chars")


@query("SELECT f AS format, (SELECT count(*) FROM labels) AS n, CAST(0 AS BIGINT) AS n_changed FROM (VALUES ('csv'), ('json'), ('orc'), ('parquet')) AS x(f)")
def scan_formats(spark: SparkSession, sf: str) -> DataFrame:
    """Written to each format in shared storage and read again with a fixed schema."""
    rows = tables.read_table(spark, sf, "labels").select("doc_id", "quality", "toxic")
    base = f"{shared_dir(spark).rstrip('/')}/formats_{uuid.uuid4().hex}"
    out = None
    for fmt in ("csv", "json", "orc", "parquet"):
        rows.write.format(fmt).save(f"{base}/{fmt}")
        again = spark.read.schema(tables.SCHEMAS["labels"]).format(fmt).load(f"{base}/{fmt}")
        one = again.agg(F.lit(fmt).alias("format"), F.count("*").alias("n")).crossJoin(rows.exceptAll(again).agg(F.count("*").alias("n_changed")))
        out = one if out is None else out.union(one)
    return out


@query(r"""WITH a AS (SELECT page_id, regexp_replace(html, '<(script|style)[^>]*>.*?</(script|style)>', ' ', 'gis') AS t, regexp_extract(html, '(?is)<title>(.*?)</title>', 1) AS title FROM pages), b AS (SELECT page_id, title, regexp_replace(t, '<[^>]*>', ' ', 'gs') AS t FROM a), c AS (SELECT page_id, title, replace(replace(replace(replace(replace(t, '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&nbsp;', ' '), '&amp;', '&') AS t FROM b)
SELECT page_id AS doc_id, md5(trim(regexp_replace(t, '\s+', ' ', 'g'))) AS text_md5, title FROM c""")
def pages_text(spark: SparkSession, sf: str) -> DataFrame:
    return tables.pages_text(spark, sf).select("doc_id", F.md5(F.col("text").cast("binary")).alias("text_md5"), "title")


@query("SELECT conv_id AS doc_id, string_agg(text, chr(10) ORDER BY turn, text) AS text, count(*) AS n_turns FROM conversations GROUP BY conv_id")
def conversation_docs(spark: SparkSession, sf: str) -> DataFrame:
    return tables.conversation_docs(spark, sf).select("doc_id", "text", F.col("n_turns").cast("bigint").alias("n_turns"))


@query(f"SELECT doc_id, CAST(len({WORDS}) AS BIGINT) AS n_tokens FROM documents")
def token_counts(spark: SparkSession, sf: str) -> DataFrame:
    return tokens(spark, sf).select("doc_id", F.size("words").cast("bigint").alias("n_tokens"))


_SENTENCES = r"list_filter(regexp_split_to_array(coalesce(text, ''), '[.!?\n]+'), lambda s: trim(s) <> '')"
SENT = rf"""s0 AS (SELECT doc_id, unnest({_SENTENCES}) AS s, generate_subscripts({_SENTENCES}, 1) - 1 AS sent_no FROM documents), sent AS (SELECT doc_id, CAST(sent_no AS INT) AS sent_no, regexp_extract_all(lower(s), '\p{{L}}+') AS words FROM s0 WHERE regexp_matches(s, '\p{{L}}'))"""


@query(f"WITH {SENT} SELECT doc_id, sent_no, CAST(len(words) AS BIGINT) AS n FROM sent")
def sentence_rows(spark: SparkSession, sf: str) -> DataFrame:
    return C.sentence_rows(documents(spark, sf)).select("doc_id", "sent_no", F.size("words").cast("bigint").alias("n"))


@query(f"WITH {TOK} SELECT term, count(*) AS tf FROM tok WHERE NOT list_contains({_list(T.stop_list())}, term) GROUP BY term")
def stopword_filtered(spark: SparkSession, sf: str) -> DataFrame:
    tok = C.tokens(documents(spark, sf), stop=T.stop_list())
    return tok.select(F.explode("words").alias("term")).groupBy("term").agg(F.count("*").alias("tf"))


@query(rf"SELECT 'documents' AS src, doc_id AS id FROM documents WHERE len({WORDS}) < 3 UNION ALL SELECT 'part', p_partkey FROM part WHERE len(regexp_extract_all(lower(p_name), '\p{{L}}+')) < 3")
def short_documents(spark: SparkSession, sf: str) -> DataFrame:
    docs = tokens(spark, sf).where(F.size("words") < 3).select(F.lit("documents").alias("src"), F.col("doc_id").alias("id"))
    names = tables.read_table(spark, sf, "part").where(F.size(T.words(F.col("p_name"))) < 3).select(F.lit("part").alias("src"), F.col("p_partkey").cast("bigint").alias("id"))
    return docs.union(names)


@query(f"WITH {TOK}, {CNT}, {vocab_sql()} SELECT term, term_id, df, tf FROM vocab")
def vocab_df_tf(spark: SparkSession, sf: str) -> DataFrame:
    return C.vocabulary(tokens(spark, sf))


@query(f"WITH {bags_sql(min_df=5)} SELECT doc_id, l AS len, term_id, c FROM kept")
def bag_rows(spark: SparkSession, sf: str) -> DataFrame:
    _, bags, _ = prepared(spark, sf, min_df=5)
    return bags.select("doc_id", "len", F.explode(F.arrays_zip("terms", "counts")).alias("t")).select("doc_id", "len", F.col("t.terms").alias("term_id"), F.col("t.counts").cast("bigint").alias("c"))


@query(f"WITH {bags_sql(200)} SELECT doc_id, string_agg(term_id || ':' || c, ' ' ORDER BY term_id) AS bag FROM kept GROUP BY doc_id")
def bag_arrays(spark: SparkSession, sf: str) -> DataFrame:
    _, bags, _ = prepared(spark, sf, 200)
    return bags.select("doc_id", F.array_join(F.zip_with("terms", "counts", lambda t, c: F.concat_ws(":", t.cast("string"), c.cast("bigint").cast("string"))), " ").alias("bag"))


@query("SELECT sha256(text) AS h, count(*) AS n, min(doc_id) AS first_id FROM documents WHERE text IS NOT NULL GROUP BY text HAVING count(*) > 1")
def exact_copies(spark: SparkSession, sf: str) -> DataFrame:
    rows = documents(spark, sf).where("text is not null").select("doc_id", F.sha2(F.col("text").cast("binary"), 256).alias("h"))
    return rows.groupBy("h").agg(F.count("*").alias("n"), F.min("doc_id").alias("first_id")).where("n > 1")


@query("SELECT min(doc_id) AS doc_id FROM documents WHERE text IS NOT NULL GROUP BY text")
def dedupe(spark: SparkSession, sf: str) -> DataFrame:
    return C.dedupe(documents(spark, sf)).select("doc_id")


def _stem_sql(word: str) -> str:
    whens = " ".join(f"WHEN regexp_matches({word}, '^.*{p}') THEN regexp_replace({word}, '{p}', '{r.replace('$1', chr(92) + '1')}')" for p, r in T.STEM_RULES)
    return f"CASE {whens} ELSE {word} END"


@query(f"WITH {TOK} SELECT {_stem_sql('term')} AS stem, count(*) AS tf FROM tok GROUP BY 1")
def stemmed_vocab(spark: SparkSession, sf: str) -> DataFrame:
    return C.tokens(documents(spark, sf), stems=True).select(F.explode("words").alias("stem")).groupBy("stem").agg(F.count("*").alias("tf"))


@query(f"WITH t AS (SELECT doc_id, {WORDS} AS w FROM documents) SELECT doc_id, CAST(least(len(w), 100) AS BIGINT) AS n FROM t")
def capped_tokens(spark: SparkSession, sf: str) -> DataFrame:
    """A sampling operator: at most 100 tokens of each document, drawn by hash."""
    return C.cap_tokens(tokens(spark, sf), 100).select("doc_id", F.size("words").cast("bigint").alias("n"))


@query(f"WITH {TOK} SELECT lang, count(DISTINCT term) AS n FROM tok GROUP BY lang")
def distinct_terms(spark: SparkSession, sf: str) -> DataFrame:
    words = documents(spark, sf).select("lang", F.explode(T.words(F.col("text"))).alias("term"))
    return words.groupBy("lang").agg(F.countDistinct("term").alias("n"))


@query("SELECT true AS within, true AS within_sketch")
def approx_terms(spark: SparkSession, sf: str) -> DataFrame:
    words = documents(spark, sf).select(F.explode(T.words(F.col("text"))).alias("term"))
    both = words.agg(F.countDistinct("term").alias("n"), F.approx_count_distinct("term", 0.01).alias("a"), F.hll_sketch_estimate(F.hll_sketch_agg("term", F.lit(14))).alias("h"))
    return both.select((F.abs(F.col("a") / F.col("n") - 1) < 0.05).alias("within"), (F.abs(F.col("h") / F.col("n") - 1) < 0.05).alias("within_sketch"))


@query(f"WITH t AS (SELECT lang, len({WORDS}) AS n FROM documents) SELECT lang, {', '.join(f'quantile_cont(n, {q}) + 0.0 AS q{int(q * 100)}' for q in (0.25, 0.5, 0.75, 0.95))} FROM t GROUP BY lang")
def length_quantiles(spark: SparkSession, sf: str) -> DataFrame:
    rows = documents(spark, sf).select("lang", F.size(T.words(F.col("text"))).alias("n"))
    return rows.groupBy("lang").agg(*(F.percentile("n", F.lit(q)).alias(f"q{int(q * 100)}") for q in (0.25, 0.5, 0.75, 0.95)))


@query(f"""WITH {TOK}, a AS (SELECT DISTINCT lang, term FROM tok), en AS (SELECT term FROM a WHERE lang = 'en'), fr AS (SELECT term FROM a WHERE lang = 'fr')
SELECT 'intersect' AS op, count(*) AS n FROM (SELECT * FROM en INTERSECT SELECT * FROM fr) UNION ALL SELECT 'except', count(*) FROM (SELECT * FROM en EXCEPT SELECT * FROM fr) UNION ALL SELECT 'union', count(*) FROM (SELECT * FROM en UNION SELECT * FROM fr)
UNION ALL SELECT 'union_all', count(*) FROM (SELECT * FROM en UNION ALL SELECT * FROM fr)""")
def vocab_set_ops(spark: SparkSession, sf: str) -> DataFrame:
    words = documents(spark, sf).select("lang", F.explode(T.words(F.col("text"))).alias("term"))
    en, fr = words.where("lang = 'en'").select("term").distinct(), words.where("lang = 'fr'").select("term").distinct()
    made = {"intersect": en.intersect(fr), "except": en.subtract(fr), "union": en.union(fr).distinct(), "union_all": en.unionAll(fr)}
    out = None
    for name, df in made.items():
        one = df.agg(F.lit(name).alias("op"), F.count("*").alias("n"))
        out = one if out is None else out.union(one)
    return out


@query(f"WITH {TOK}, c AS (SELECT lang, term, count(*) AS tf FROM tok GROUP BY ALL) SELECT lang, term, tf, CAST(row_number() OVER (PARTITION BY lang ORDER BY tf DESC, term) AS INT) AS rank FROM c QUALIFY rank <= 10")
def top_words_per_lang(spark: SparkSession, sf: str) -> DataFrame:
    words = documents(spark, sf).select("lang", F.explode(T.words(F.col("text"))).alias("term")).groupBy("lang", "term").agg(F.count("*").alias("tf"))
    return words.withColumn("rank", F.row_number().over(Window.partitionBy("lang").orderBy(F.col("tf").desc(), "term"))).where("rank <= 10")


@query(f"WITH {TOK} SELECT term, count(*) AS tf FROM tok GROUP BY term ORDER BY tf DESC, term LIMIT 25")
def top_words(spark: SparkSession, sf: str) -> DataFrame:
    return tokens(spark, sf).select(F.explode("words").alias("term")).groupBy("term").agg(F.count("*").alias("tf")).orderBy(F.col("tf").desc(), "term").limit(25)


@query(f"WITH {TOK}, f AS (SELECT term, min(doc_id) AS doc_id FROM tok GROUP BY term), n AS (SELECT doc_id, count(*) AS new FROM f GROUP BY doc_id) SELECT doc_id, new, CAST(sum(new) OVER (ORDER BY doc_id) AS BIGINT) AS seen FROM n")
def running_vocab(spark: SparkSession, sf: str) -> DataFrame:
    """New words up to each document.  The running sum is made in ranges of doc_id, so no task holds all documents."""
    first = tokens(spark, sf).select("doc_id", F.explode("words").alias("term")).groupBy("term").agg(F.min("doc_id").alias("doc_id"))
    new = first.groupBy("doc_id").agg(F.count("*").alias("new")).withColumn("block", F.floor(F.col("doc_id") / 10_000))
    before = new.groupBy("block").agg(F.sum("new").alias("n"))
    before = before.select("block", (F.sum("n").over(Window.orderBy("block")) - F.col("n")).alias("before"))
    inside = F.sum("new").over(Window.partitionBy("block").orderBy("doc_id").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    return new.withColumn("inside", inside).join(before, "block").select("doc_id", "new", (F.col("before") + F.col("inside")).alias("seen"))


@query("SELECT doc_id FROM documents WHERE CAST('0x' || substr(md5(CAST(doc_id AS VARCHAR)), 1, 4) AS INT) % 10 = 0")
def sampled_fraction(spark: SparkSession, sf: str) -> DataFrame:
    """A sampling operator: a tenth of the documents by the hash of their id."""
    return documents(spark, sf).where(F.conv(F.substring(F.md5(F.col("doc_id").cast("string").cast("binary")), 1, 4), 16, 10).cast("int") % 10 == 0).select("doc_id")


@query(f"WITH {SENT}, p AS (SELECT doc_id, sent_no, unnest(words) AS w, generate_subscripts(words, 1) AS pos FROM sent), b AS (SELECT w AS w1, lead(w) OVER (PARTITION BY doc_id, sent_no ORDER BY pos) AS w2 FROM p) SELECT w1, w2, count(*) AS n FROM b WHERE w2 IS NOT NULL GROUP BY ALL")
def lead_bigrams(spark: SparkSession, sf: str) -> DataFrame:
    words = C.sentence_rows(documents(spark, sf)).select("doc_id", "sent_no", F.posexplode("words").alias("pos", "w1"))
    paired = words.withColumn("w2", F.lead("w1").over(Window.partitionBy("doc_id", "sent_no").orderBy("pos")))
    return paired.where("w2 is not null").groupBy("w1", "w2").agg(F.count("*").alias("n"))


@query(f"WITH {bags_sql(200)} SELECT x.doc_id, x.term_id, {'round(c / sum(c) OVER (PARTITION BY x.doc_id), 6) + 0.0'} AS share FROM lb x")
def doc_share(spark: SparkSession, sf: str) -> DataFrame:
    _, long = long_prepared(spark, sf, 200)
    return long.select("doc_id", "term_id", r6(F.col("c") / F.sum("c").over(Window.partitionBy("doc_id"))).alias("share"))


@query(f"WITH {TOK}, {CNT}, {vocab_sql()} SELECT term, CAST(rank() OVER (ORDER BY tf DESC) AS INT) AS rank, CAST(dense_rank() OVER (ORDER BY tf DESC) AS INT) AS dense_rank, round(percent_rank() OVER (ORDER BY tf DESC), 6) AS percent_rank, round(cume_dist() OVER (ORDER BY tf DESC), 6) AS cume_dist, CAST(ntile(10) OVER (ORDER BY tf DESC, term) AS INT) AS ntile FROM vocab")
def rank_functions(spark: SparkSession, sf: str) -> DataFrame:
    """Ranks of all words by their occurrences."""
    ranked = C.frequency_ranks(C.vocabulary(tokens(spark, sf)), "term")
    return ranked.select("term", "rank", "dense_rank", F.round("percent_rank", 6).alias("percent_rank"), F.round("cume_dist", 6).alias("cume_dist"), "ntile")

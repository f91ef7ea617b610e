"""Relational operators around the methods: joins, aggregates, windows, functions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from momenttree.functions import udfs
from momenttree.functions.text import page_title
from momenttree.operators import assign as A
from momenttree.operators import corpus as C
from momenttree.queries import query
from momenttree.queries.shared import LANG_SQL, bags_sql, documents, lang_topics, lang_weights, long_prepared, prepared, r6, r6_sql
from momenttree.runtime import ship
from momenttree.sources.tables import read_table

_HARD = f"WITH {bags_sql(200)}, {LANG_SQL}, t AS (SELECT doc_id, path, sum(c * omega) AS n FROM lb JOIN omega USING (term_id) GROUP BY ALL), s AS (SELECT doc_id, path, n / sum(n) OVER (PARTITION BY doc_id) AS theta FROM t), hard AS (SELECT doc_id, arg_min(path, (-round(theta, 9), path)) AS path FROM s GROUP BY doc_id), cube_in AS (SELECT d.lang, h.path, l.quality FROM hard h JOIN documents d USING (doc_id) LEFT JOIN labels l USING (doc_id))"


def _hard(spark: SparkSession, sf: str) -> DataFrame:
    """lang, path, quality of every document with known words; path is its largest topic."""
    _, long, nodes, words = lang_topics(spark, sf, 200)
    theta = A.assign(long, lang_weights(nodes, words))
    best = theta.groupBy("doc_id").agg(F.min(F.struct((-F.round("theta", 9)).alias("order"), "path")).alias("b")).select("doc_id", F.col("b.path").alias("path"))
    return best.join(documents(spark, sf).select("doc_id", "lang"), "doc_id").join(read_table(spark, sf, "labels").select("doc_id", "quality"), "doc_id", "left").select("lang", "path", "quality")


_GROUPED = "SELECT lang, path, CAST(grouping(lang) * 2 + grouping(path) AS BIGINT) AS gid, count(*) AS n, count(quality) AS n_labelled FROM cube_in GROUP BY"


def _grouped(made) -> DataFrame:
    return made.agg(F.grouping_id().cast("bigint").alias("gid"), F.count("*").alias("n"), F.count("quality").alias("n_labelled"))


@query(f"{_HARD} {_GROUPED} CUBE (lang, path)")
def topic_cube(spark: SparkSession, sf: str) -> DataFrame:
    return _grouped(_hard(spark, sf).cube("lang", "path"))


@query(f"{_HARD} {_GROUPED} ROLLUP (lang, path)")
def topic_rollup(spark: SparkSession, sf: str) -> DataFrame:
    return _grouped(_hard(spark, sf).rollup("lang", "path"))


@query(f"{_HARD} {_GROUPED} GROUPING SETS ((lang), (path))")
def topic_grouping_sets(spark: SparkSession, sf: str) -> DataFrame:
    return _grouped(_hard(spark, sf).groupingSets([["lang"], ["path"]], "lang", "path"))


@query(f"{_HARD}, g AS (SELECT lang, path, count(*) AS n FROM cube_in GROUP BY ALL), a AS (SELECT l.lang, p.path FROM (SELECT DISTINCT lang FROM cube_in) l CROSS JOIN (SELECT 'o/' || i AS path FROM range(1, 5) t(i)) p) SELECT a.lang, a.path, coalesce(n, 0) AS n FROM a LEFT JOIN g ON g.lang = a.lang AND g.path = a.path")
def topic_pivot(spark: SparkSession, sf: str) -> DataFrame:
    """Language by topic as a matrix, and back to rows."""
    names = [f"o/{k}" for k in range(1, 5)]
    wide = _hard(spark, sf).groupBy("lang").pivot("path", names).agg(F.count(F.lit(1))).na.fill(0)
    return wide.unpivot(["lang"], names, "path", "n")


@query("SELECT doc_id, doc_id IN (SELECT doc_id FROM labels) AS labelled FROM documents")
def labelled_docs(spark: SparkSession, sf: str) -> DataFrame:
    docs, labels = documents(spark, sf).select("doc_id"), read_table(spark, sf, "labels").select("doc_id")
    return docs.join(labels, "doc_id", "left_semi").withColumn("labelled", F.lit(True)).union(docs.join(labels, "doc_id", "left_anti").withColumn("labelled", F.lit(False)))


@query("SELECT lang, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents WHERE lang = 'de' AND n_chars > 1000 GROUP BY lang")
def lang_filter(spark: SparkSession, sf: str) -> DataFrame:
    """Both filters reach the Parquet scan, which reads two columns."""
    return documents(spark, sf).where("lang = 'de' and n_chars > 1000").groupBy("lang").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@query("SELECT r_name, p_brand, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey JOIN part ON l_partkey = p_partkey GROUP BY ALL")
def star_join(spark: SparkSession, sf: str) -> DataFrame:
    """Brand mix by region: nation and region are fixed small tables, the others are left to size-based choice."""
    t = lambda name: read_table(spark, sf, name)
    small = t("nation").join(t("region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")
    customers = t("customer").join(F.broadcast(small), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "r_name")
    orders = t("orders").join(customers, F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "r_name")
    items = t("lineitem").select("l_orderkey", "l_partkey", "l_quantity").join(t("part").select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
    return items.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("r_name", "p_brand").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


@query(f"WITH {bags_sql(100)}, a AS (SELECT term_id, CAST(sum(c) AS DOUBLE) / sum(sum(c)) OVER () AS phi FROM lb WHERE lang = 'en' GROUP BY term_id), b AS (SELECT term_id, CAST(sum(c) AS DOUBLE) / sum(sum(c)) OVER () AS phi FROM lb WHERE lang = 'fr' GROUP BY term_id) SELECT coalesce(a.term_id, b.term_id) AS term_id, round(a.phi, 9) AS phi_a, round(b.phi, 9) AS phi_b FROM a FULL OUTER JOIN b ON a.term_id = b.term_id")
def topics_outer(spark: SparkSession, sf: str) -> DataFrame:
    """Words of two topics side by side."""
    _, long = long_prepared(spark, sf, 100)
    by = long.join(documents(spark, sf).select("doc_id", "lang"), "doc_id")

    def words(lang: str, name: str) -> DataFrame:
        own = by.where(F.col("lang") == lang).groupBy("term_id").agg(F.sum("c").alias("c"))
        return own.select("term_id", F.round(F.col("c") / F.sum("c").over(Window.partitionBy()), 9).alias(name))

    return words("en", "phi_a").join(words("fr", "phi_b"), "term_id", "full_outer")


@query("SELECT e.user_id, e.event_id AS error_id, count(*) AS n FROM events e JOIN events p ON p.user_id = e.user_id AND p.ts BETWEEN e.ts - INTERVAL 1 HOUR AND e.ts + INTERVAL 1 HOUR WHERE e.event_type = 'error' AND p.event_type = 'purchase' GROUP BY ALL")
def event_range_join(spark: SparkSession, sf: str) -> DataFrame:
    """Purchases within an hour of an error of the same user: both sides are dealt to hour buckets, the error to three."""
    events = read_table(spark, sf, "events")
    hour = F.floor(F.unix_timestamp("ts") / 3600)
    errors = events.where("event_type = 'error'").select("user_id", F.col("event_id").alias("error_id"), F.col("ts").alias("at"), F.explode(F.array(hour - 1, hour, hour + 1)).alias("bucket"))
    buys = events.where("event_type = 'purchase'").select("user_id", "ts", hour.alias("bucket"))
    near = (F.col("ts") >= F.col("at") - F.expr("INTERVAL 1 HOUR")) & (F.col("ts") <= F.col("at") + F.expr("INTERVAL 1 HOUR"))
    return errors.join(buys, ["user_id", "bucket"]).where(near).groupBy("user_id", "error_id").agg(F.count("*").alias("n"))


@query("WITH p AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'purchase'), v AS (SELECT event_id AS view_id, user_id, ts AS vts FROM events WHERE event_type = 'view') SELECT p.event_id, (SELECT max(struct_pack(vts := v.vts, id := v.view_id)).id FROM v WHERE v.user_id = p.user_id AND v.vts < p.ts) AS view_id FROM p")
def event_asof(spark: SparkSession, sf: str) -> DataFrame:
    """The last view strictly before each purchase of the same user: one sort of the union by user and time."""
    events = read_table(spark, sf, "events").where("event_type in ('purchase', 'view')")
    seen = F.when(F.col("event_type") == "view", F.col("event_id"))
    order = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "view", 1).otherwise(0), "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return events.withColumn("view_id", F.last(seen, ignorenulls=True).over(order)).where("event_type = 'purchase'").select("event_id", "view_id")


@query("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY epoch(date_trunc('second', ts)) RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW), 6) AS mean FROM events")
def event_moving(spark: SparkSession, sf: str) -> DataFrame:
    order = Window.partitionBy("user_id").orderBy(F.unix_timestamp("ts")).rangeBetween(-3600, Window.currentRow)
    return read_table(spark, sf, "events").select("event_id", F.round(F.avg("value").over(order), 6).alias("mean"))


@query("SELECT p_partkey AS id, upper(trim(p_name)) AS name, split_part(p_brand, '#', 1) AS brand, length(p_name) AS len, levenshtein(p_name, p_type) AS lev, concat_ws('-', p_brand, p_type) AS joined, regexp_replace(p_name, '[aeiou]', '', 'g') AS consonants FROM part")
def string_functions(spark: SparkSession, sf: str) -> DataFrame:
    return read_table(spark, sf, "part").select(
        F.col("p_partkey").alias("id"), F.upper(F.trim("p_name")).alias("name"), F.substring_index("p_brand", "#", 1).alias("brand"), F.length("p_name").cast("bigint").alias("len"),
        F.levenshtein("p_name", "p_type").cast("bigint").alias("lev"), F.concat_ws("-", "p_brand", "p_type").alias("joined"), F.regexp_replace("p_name", "[aeiou]", "").alias("consonants"),
    )


@query("SELECT page_id, regexp_extract(html, '(?is)<title>(.*?)</title>', 1) AS title, split_part(split_part(url, '://', 2), '/', 1) AS host FROM pages")
def page_titles(spark: SparkSession, sf: str) -> DataFrame:
    return read_table(spark, sf, "pages").select("page_id", page_title(F.col("html")).alias("title"), F.split_part(F.split_part("url", F.lit("://"), F.lit(2)), F.lit("/"), F.lit(1)).alias("host"))


@query("SELECT date_trunc('month', o_orderdate) AS month, CAST(isodow(o_orderdate) AS BIGINT) AS dow, count(*) AS n, CAST(max(date_diff('day', CAST(DATE '1992-01-01' AS TIMESTAMP), date_trunc('day', o_orderdate))) AS BIGINT) AS last_day FROM orders GROUP BY ALL")
def date_functions(spark: SparkSession, sf: str) -> DataFrame:
    rows = read_table(spark, sf, "orders").select(F.date_trunc("month", "o_orderdate").alias("month"), (F.weekday("o_orderdate") + 1).cast("bigint").alias("dow"), F.datediff("o_orderdate", F.lit("1992-01-01")).cast("bigint").alias("d"))
    return rows.groupBy("month", "dow").agg(F.count("*").alias("n"), F.max("d").alias("last_day"))


@query("SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 5) AS norm2, round(CAST(embedding[1] AS DOUBLE) * embedding[2], 6) + 0.0 AS first_two, CAST(len(list_filter(embedding, lambda x: x > 0)) AS BIGINT) AS n_positive FROM embeddings")
def array_functions(spark: SparkSession, sf: str) -> DataFrame:
    e = F.transform("embedding", lambda x: x.cast("double"))
    norm = F.aggregate(F.zip_with(e, e, lambda a, b: a * b), F.lit(0.0), lambda a, x: a + x)
    return read_table(spark, sf, "embeddings").select("vec_id", F.round(norm, 5).alias("norm2"), r6(F.get(e, F.lit(0)) * F.get(e, F.lit(1))).alias("first_two"), F.size(F.filter("embedding", lambda x: x > 0)).cast("bigint").alias("n_positive"))


@query(f"WITH {bags_sql(100)} SELECT doc_id, {r6_sql('sum(c * (term_id + 1) / 100.0)')} AS dot, coalesce(max(CASE WHEN term_id = 0 THEN c END), 0) AS first FROM kept GROUP BY doc_id")
def sparse_vectors(spark: SparkSession, sf: str) -> DataFrame:
    """A bag as a map from word to count, and its product with a dense vector."""
    _, bags, v = prepared(spark, sf, 100)
    weights = F.array(*(F.lit((x + 1) / 100.0) for x in range(v)))
    lookup = F.coalesce(F.element_at(F.map_from_arrays("terms", "counts"), F.lit(0)), F.lit(0.0))
    return bags.select("doc_id", r6(udfs.sparse_dot(F.col("terms"), F.col("counts"), weights)).alias("dot"), lookup.cast("bigint").alias("first"))


@query("SELECT CAST(floor(CAST(json_extract_string(props, '$.k') AS INT) / 10.0) AS BIGINT) AS bucket, count(*) AS n FROM events GROUP BY 1")
def json_bucket(spark: SparkSession, sf: str) -> DataFrame:
    rows = read_table(spark, sf, "events").select(F.from_json("props", "k int").alias("p"))
    return rows.select(F.floor(F.col("p.k") / 10).alias("bucket")).groupBy("bucket").agg(F.count("*").alias("n"))


@query("SELECT CAST(floor(CAST(json_extract_string(props, '$.k') AS INT) / 10.0) AS BIGINT) AS bucket, count(*) AS n FROM events GROUP BY 1")
def json_variant(spark: SparkSession, sf: str) -> DataFrame:
    rows = read_table(spark, sf, "events").select(F.try_variant_get(F.try_parse_json("props"), "$.k", "int").alias("k"))
    return rows.select(F.floor(F.col("k") / 10).alias("bucket")).groupBy("bucket").agg(F.count("*").alias("n"))


@query(f"WITH {bags_sql(200)}, {LANG_SQL}, g AS (SELECT a.path AS a, b.path AS b FROM langs a CROSS JOIN langs b), t AS (SELECT DISTINCT term_id FROM phi), f AS (SELECT path, term_id, coalesce(phi, 0) + 1e-12 AS phi FROM (SELECT path, term_id FROM langs CROSS JOIN t) LEFT JOIN phi USING (path, term_id)), n AS (SELECT path, term_id, phi / sum(phi) OVER (PARTITION BY path) AS phi FROM f) SELECT g.a, g.b, {r6_sql('sum(x.phi * ln(x.phi / y.phi))')} AS kl FROM g JOIN n x ON x.path = g.a JOIN n y ON y.path = g.b AND x.term_id = y.term_id GROUP BY ALL")
def udf_kl(spark: SparkSession, sf: str) -> DataFrame:
    """The pandas UDF on dense arrays of topics."""
    ship(spark)
    vocab, _, nodes, words = lang_topics(spark, sf, 200)
    full = nodes.select("path").crossJoin(F.broadcast(vocab.select("term_id"))).join(words, ["path", "term_id"], "left").groupBy("path").agg(F.array_sort(F.collect_list(F.struct("term_id", F.coalesce("phi", F.lit(0.0)).alias("phi")))).alias("p"))
    dense = full.select("path", F.col("p.phi").alias("phi"))
    pairs = dense.toDF("a", "pa").crossJoin(dense.toDF("b", "pb"))
    return pairs.select("a", "b", r6(udfs.kl_divergence()("pa", "pb")).alias("kl"))


@query("SELECT label, round(sum(CAST(embedding[1] AS DOUBLE)), 4) + 0.0 AS first_sum FROM embeddings GROUP BY label")
def udf_vector_sum(spark: SparkSession, sf: str) -> DataFrame:
    """The grouped aggregate pandas UDF.  Groups go to Python whole, so partial sums by hash of the id come first."""
    ship(spark)
    rows = read_table(spark, sf, "embeddings").select("label", F.pmod(F.xxhash64("vec_id"), F.lit(64)).alias("salt"), F.col("embedding").cast("array<double>").alias("e"))
    parts = rows.groupBy("label", "salt").agg(udfs.vector_sum()("e").alias("e"))
    return parts.groupBy("label").agg(udfs.vector_sum()("e").alias("e")).select("label", (F.round(F.col("e")[0], 4) + F.lit(0.0)).alias("first_sum"))


@query(r"WITH t AS (SELECT item_id, regexp_extract_all(lower(coalesce(text, '')), '\p{L}+') AS w FROM benchmark) SELECT item_id, CAST(sum(CASE WHEN len(w) >= 1 THEN len(w) ELSE 0 END + CASE WHEN len(w) >= 2 THEN len(w) - 1 ELSE 0 END) AS BIGINT) AS n FROM t WHERE len(w) > 0 GROUP BY item_id")
def udtf_ngrams(spark: SparkSession, sf: str) -> DataFrame:
    """The table function joined laterally."""
    ship(spark)
    tok = C.tokens(read_table(spark, sf, "benchmark").withColumnRenamed("item_id", "doc_id"))
    made = tok.lateralJoin(udfs.ngrams()(F.col("words").outer(), F.lit(1), F.lit(2)))
    return made.groupBy(F.col("doc_id").alias("item_id")).agg(F.count("*").alias("n"))


@query("WITH p AS (SELECT split_part(p_brand, '#', 2) AS b, CAST(p_size AS VARCHAR) AS s FROM part), a AS (SELECT CAST(0 AS INT) AS level, 'o' AS ancestor, CAST(NULL AS VARCHAR) AS own_parent FROM p UNION ALL SELECT 1, 'o/' || b, 'o' FROM p UNION ALL SELECT 2, 'o/' || b || '/' || s, 'o/' || b FROM p) SELECT level, ancestor, level AS own_level, own_parent, count(*) AS n FROM a GROUP BY ALL")
def sql_surface(spark: SparkSession, sf: str) -> DataFrame:
    """Registered names from SQL: brands and, below them, sizes as paths; parts at and below each."""
    ship(spark)
    udfs.register(spark)
    parts = read_table(spark, sf, "part").select(F.concat_ws("/", F.lit("o"), F.split_part("p_brand", F.lit("#"), F.lit(2)), "p_size").alias("path"))
    return spark.sql("SELECT a.level, a.ancestor, topic_level(a.ancestor) AS own_level, topic_parent(a.ancestor) AS own_parent, count(*) AS n FROM {parts} p, LATERAL ancestors(p.path) a GROUP BY a.level, a.ancestor", parts=parts)

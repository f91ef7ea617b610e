"""Moments, and model quantities on languages as known topics."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from momenttree.evaluation import measures
from momenttree.functions import tensor as X
from momenttree.operators import assign as A
from momenttree.operators import moments as M
from momenttree.operators import tree as TT
from momenttree.queries import query
from momenttree.queries.shared import LANG_SQL, bags_sql, lang_topics, lang_weights, long_prepared, prepared, r6, r6_sql
from momenttree.runtime import stored
from momenttree.sources import tables

E6 = 1e6
#: The spectral vocabulary; pair tables over all four languages, and triples, take fewer words so that their SQL twins can follow.
TOP, PAIRED, TRIPLED = 1_500, 500, 60
PAIR_SQL = "sum((a.c * b.c - CASE WHEN a.term_id = b.term_id THEN a.c ELSE 0 END) / (a.l * (a.l - 1)))"
E2_SQL = f"e2 AS (SELECT a.term_id AS x1, b.term_id AS x2, {PAIR_SQL} / (SELECT d FROM d) AS v FROM kept a JOIN kept b ON a.doc_id = b.doc_id AND a.term_id <= b.term_id GROUP BY ALL HAVING {PAIR_SQL} > 1e-15)"


@query(f"WITH {bags_sql(min_df=5)} SELECT term_id, {r6_sql('sum(c / l) / (SELECT d FROM d)', E6)} AS m1 FROM kept GROUP BY term_id")
def first_moment(spark: SparkSession, sf: str) -> DataFrame:
    _, bags, v = prepared(spark, sf, min_df=5)
    return M.first_moment(bags, v).select(F.col("x").alias("term_id"), r6("v", E6).alias("m1"))


@query(f"WITH {bags_sql(TOP)}, {E2_SQL} SELECT x1, x2, {r6_sql('v', E6)} AS e2 FROM e2")
def second_moment(spark: SparkSession, sf: str) -> DataFrame:
    _, bags, v = prepared(spark, sf, TOP)
    return M.second_moment(bags, v).select("x1", "x2", r6("v", E6).alias("e2"))


@query(f"WITH {bags_sql(TOP)}, {E2_SQL} SELECT x1, x2, {r6_sql('v', E6)} AS e2 FROM e2")
def second_moment_selfjoin(spark: SparkSession, sf: str) -> DataFrame:
    _, long = long_prepared(spark, sf, TOP)
    return M.second_moment_sql(long).select("x1", "x2", r6("v", E6).alias("e2"))


@query(f"WITH {bags_sql(min_df=5)}, q AS (SELECT doc_id, sum(c * (term_id % 7)) AS t FROM kept GROUP BY doc_id) SELECT term_id AS x, {r6_sql('sum((c * t - c * (term_id % 7)) / (l * (l - 1))) / (SELECT d FROM d)', E6)} AS y FROM kept JOIN q USING (doc_id) GROUP BY term_id HAVING sum((c * t - c * (term_id % 7)) / (l * (l - 1))) > 0")
def second_moment_apply(spark: SparkSession, sf: str) -> DataFrame:
    """E2 times a vector without forming a pair."""
    _, bags, v = prepared(spark, sf, min_df=5)
    rows = M.second_moment_apply(bags, v, {"o": (np.arange(v) % 7).astype(float)[:, None]}).cache()
    docs = rows.where("x = -1").select(F.col("y")[0].alias("d"))
    return rows.where("x >= 0").crossJoin(F.broadcast(docs)).select("x", r6(F.col("y")[0] / F.col("d"), E6).alias("y"))


_ROOT_TRIPLE = "a.c * b.c * g.c - CASE WHEN a.term_id = b.term_id THEN a.c * g.c ELSE 0 END - CASE WHEN b.term_id = g.term_id THEN a.c * b.c ELSE 0 END - CASE WHEN a.term_id = g.term_id THEN a.c * b.c ELSE 0 END + CASE WHEN a.term_id = b.term_id AND b.term_id = g.term_id THEN 2 * a.c ELSE 0 END"


@query(f"WITH {bags_sql(TRIPLED)}, t AS (SELECT a.term_id AS x1, b.term_id AS x2, g.term_id AS x3, sum(({_ROOT_TRIPLE}) / (a.l * (a.l - 1) * (a.l - 2))) / (SELECT d FROM d) AS v FROM kept a JOIN kept b ON a.doc_id = b.doc_id AND a.term_id <= b.term_id JOIN kept g ON a.doc_id = g.doc_id AND b.term_id <= g.term_id GROUP BY ALL) SELECT x1, x2, x3, {r6_sql('v', E6)} AS e3 FROM t WHERE v > 1e-15")
def third_moment(spark: SparkSession, sf: str) -> DataFrame:
    """Distinct triples of tokens of the most widespread words."""
    _, bags, v = prepared(spark, sf, TRIPLED)
    e3 = M.third_moment_dense(bags, v)
    rows = [(int(a), int(b), int(c), float(e3[a, b, c])) for a, b, c in zip(*np.nonzero(e3 > 1e-15), strict=True) if a <= b <= c]
    return spark.createDataFrame(rows, "x1 int, x2 int, x3 int, v double").select("x1", "x2", "x3", r6("v", E6).alias("e3"))


@query("SELECT 1.0 AS m1, 1.0 AS e2, 1.0 AS e3")
def moment_mass(spark: SparkSession, sf: str) -> DataFrame:
    _, bags, v = prepared(spark, sf, 200)
    bags = stored(bags, "bags")  # scanned twice
    root = M.moments_of(bags, v)["o"]
    return spark.createDataFrame([(float(root.m1.sum()), float(root.e2.sum()), float(M.third_moment_dense(bags, v).sum()))], "m1 double, e2 double, e3 double").select(r6("m1").alias("m1"), r6("e2").alias("e2"), r6("e3").alias("e3"))


_BASKETS = "tok AS (SELECT l_orderkey AS doc_id, p_brand AS term FROM lineitem JOIN part ON l_partkey = p_partkey), lb AS (SELECT doc_id, term AS term_id, count(*) AS c FROM tok GROUP BY ALL), len AS (SELECT doc_id, sum(c) AS l FROM lb GROUP BY doc_id HAVING sum(c) >= 3), kept AS (SELECT lb.*, CAST(l AS DOUBLE) AS l FROM lb JOIN len USING (doc_id)), d AS (SELECT CAST(count(*) AS DOUBLE) AS d FROM len)"


@query(f"WITH {_BASKETS}, {E2_SQL} SELECT x1 AS brand1, x2 AS brand2, {r6_sql('v', E6)} AS e2 FROM e2")
def baskets_second_moment(spark: SparkSession, sf: str) -> DataFrame:
    """Orders as documents whose words are brands, numbered in their alphabetical order."""
    tok = tables.baskets(spark, sf)
    names = tok.select(F.explode("words").alias("term")).distinct()
    from pyspark.sql import Window

    from momenttree.operators import corpus as C

    vocab = names.select("term", (F.row_number().over(Window.orderBy("term")) - 1).alias("term_id")).cache()
    v = vocab.count()
    pairs = M.second_moment(C.bags(tok, vocab, size=v), v)
    return pairs.join(F.broadcast(vocab.toDF("brand1", "x1")), "x1").join(F.broadcast(vocab.toDF("brand2", "x2")), "x2").select("brand1", "brand2", r6("v", E6).alias("e2"))


@query("""WITH w AS (SELECT user_id AS doc_id, event_type || '_' || CAST(floor(CAST(json_extract_string(props, '$.k') AS INT) / 10.0) AS BIGINT) AS term FROM events), lb AS (SELECT doc_id, term, count(*) AS c FROM w WHERE term IS NOT NULL GROUP BY ALL) SELECT doc_id, sum(c) AS n, count(*) AS n_distinct FROM lb GROUP BY doc_id""")
def user_documents(spark: SparkSession, sf: str) -> DataFrame:
    users = tables.user_docs(spark, sf)
    return users.select("doc_id", F.size("words").cast("bigint").alias("n"), F.size(F.array_distinct("words")).cast("bigint").alias("n_distinct"))


@query(f"WITH {bags_sql(TOP)}, {LANG_SQL} SELECT path, {r6_sql('alpha')} AS alpha, term_id, {r6_sql('phi', E6)} AS phi FROM phi JOIN langs USING (path)")
def lang_tree(spark: SparkSession, sf: str) -> DataFrame:
    _, _, nodes, words = lang_topics(spark, sf, TOP)
    return words.join(F.broadcast(nodes), "path").select("path", r6("alpha").alias("alpha"), "term_id", r6("phi", E6).alias("phi"))


@query(f"WITH {bags_sql(TOP)}, {LANG_SQL}, m AS (SELECT path, term_id, phi FROM phi UNION ALL SELECT 'o', term_id, sum(phi * alpha) / (SELECT sum(alpha) FROM langs) FROM phi JOIN langs USING (path) GROUP BY term_id) SELECT path, term_id, {r6_sql('phi', E6)} AS phi FROM m")
def mix_up(spark: SparkSession, sf: str) -> DataFrame:
    _, _, nodes, words = lang_topics(spark, sf, TOP)
    return TT.mix_up(nodes, words, 1).select("path", "term_id", r6("phi", E6).alias("phi"))


_POPULATION = f"WITH {bags_sql(PAIRED)}, {LANG_SQL}, a0 AS (SELECT sum(alpha) AS a0 FROM langs), q AS (SELECT a.path AS p1, b.path AS p2, a.alpha * (b.alpha + CASE WHEN a.path = b.path THEN 1 ELSE 0 END) / (a0 * (a0 + 1)) AS q FROM langs a CROSS JOIN langs b CROSS JOIN a0)"


@query(f"{_POPULATION} SELECT x.term_id AS x1, y.term_id AS x2, {r6_sql('sum(q * x.phi * y.phi)', E6)} AS m2 FROM q JOIN phi x ON x.path = p1 JOIN phi y ON y.path = p2 GROUP BY ALL")
def population_m2(spark: SparkSession, sf: str) -> DataFrame:
    """Pair probabilities that the language tree implies."""
    _, _, nodes, words = lang_topics(spark, sf, PAIRED)
    order = [(r.path, r.alpha) for r in nodes.orderBy("path").collect()]
    frame = words.toPandas()
    v = int(frame["term_id"].max()) + 1
    phi = np.zeros((v, len(order)))
    for z, (path, _) in enumerate(order):
        own = frame[frame["path"] == path]
        phi[own["term_id"], z] = own["phi"]
    m2 = X.population_moments(np.array([a for _, a in order]), phi, 2)
    x1, x2 = (a.ravel().astype(np.int32) for a in np.indices((v, v)))
    return spark.createDataFrame(pa.table({"x1": x1, "x2": x2, "m2": m2.ravel()})).select("x1", "x2", r6("m2", E6).alias("m2"))


@query(f"WITH {bags_sql(TOP)}, {LANG_SQL} SELECT term_id AS x, {r6_sql('sum(alpha * phi) / (SELECT sum(alpha) FROM langs)', E6)} AS m1 FROM phi JOIN langs USING (path) GROUP BY term_id")
def population_m1(spark: SparkSession, sf: str) -> DataFrame:
    """Word probabilities that the language tree implies."""
    _, _, nodes, words = lang_topics(spark, sf, TOP)
    frame, alpha = words.toPandas(), {r.path: r.alpha for r in nodes.collect()}
    order = sorted(alpha)
    phi = np.zeros((int(frame["term_id"].max()) + 1, len(order)))
    phi[frame["term_id"], frame["path"].map(order.index)] = frame["phi"]
    m1 = X.population_moments(np.array([alpha[p] for p in order]), phi, 1)
    return spark.createDataFrame(pa.table({"x": np.arange(len(m1), dtype=np.int32), "m1": m1})).select("x", r6("m1", E6).alias("m1"))


@query(f"WITH {bags_sql(TOP)}, {LANG_SQL} SELECT path, term_id, {r6_sql('omega')} AS omega FROM omega")
def word_weights(spark: SparkSession, sf: str) -> DataFrame:
    _, _, nodes, words = lang_topics(spark, sf, TOP)
    return lang_weights(nodes, words).select("path", "term_id", r6("omega").alias("omega"))


@query(f"WITH {bags_sql(TOP)}, {LANG_SQL} SELECT doc_id, path, {r6_sql('sum(c * omega)')} AS len_t FROM lb JOIN omega USING (term_id) GROUP BY ALL")
def topical_counts(spark: SparkSession, sf: str) -> DataFrame:
    _, long, nodes, words = lang_topics(spark, sf, TOP)
    return A.topical_counts(long, lang_weights(nodes, words)).select("doc_id", "path", r6("len_t").alias("len_t"))


@query(f"WITH {bags_sql(TOP)}, {LANG_SQL}, t AS (SELECT doc_id, path, sum(c * omega) AS n FROM lb JOIN omega USING (term_id) GROUP BY ALL) SELECT doc_id, path, {r6_sql('n / sum(n) OVER (PARTITION BY doc_id)')} AS theta FROM t")
def doc_topics(spark: SparkSession, sf: str) -> DataFrame:
    _, long, nodes, words = lang_topics(spark, sf, TOP)
    return A.assign(long, lang_weights(nodes, words)).select("doc_id", "path", r6("theta").alias("theta"))


_CHILD = f"WITH {bags_sql(PAIRED)}, {LANG_SQL}, s AS (SELECT path, doc_id, term_id, c * omega AS c FROM lb JOIN omega USING (term_id)), n AS (SELECT path, doc_id, sum(c) AS l FROM s GROUP BY ALL HAVING sum(c) >= 3), k AS (SELECT s.*, l FROM s JOIN n USING (path, doc_id)), dp AS (SELECT path, CAST(count(*) AS DOUBLE) AS dp FROM n GROUP BY path), e AS (SELECT a.path, a.term_id AS x1, b.term_id AS x2, {PAIR_SQL} AS t FROM k a JOIN k b ON a.path = b.path AND a.doc_id = b.doc_id AND a.term_id <= b.term_id GROUP BY ALL)"


@query(f"{_CHILD} SELECT path, x1, x2, {r6_sql('t / dp', 1e4)} AS e2 FROM e JOIN dp USING (path) WHERE abs(t / dp) > 1e-6")
def child_moments(spark: SparkSession, sf: str) -> DataFrame:
    """Second moments of all four children in one scan, counts weighted by each word's posterior."""
    vocab, _, nodes, words = lang_topics(spark, sf, PAIRED)
    v = vocab.count()
    weights = {}
    for r in lang_weights(nodes, words).collect():
        weights.setdefault(r.path, np.zeros(v))[r.term_id] = r.omega
    _, bags, _ = prepared(spark, sf, PAIRED)
    return M.second_moment(bags, v, weights).where("abs(v) > 1e-6").select("path", "x1", "x2", r6("v", 1e4).alias("e2"))


@query(f"WITH {bags_sql(PAIRED)}, {LANG_SQL}, {E2_SQL}, a0 AS (SELECT sum(alpha) AS a0 FROM langs), j AS (SELECT x1, x2, v, p.path AS p1, q.path AS p2, p.phi * q.phi * a.alpha * (b.alpha + CASE WHEN a.path = b.path THEN 1 ELSE 0 END) AS w FROM e2 JOIN phi p ON p.term_id = x1 JOIN phi q ON q.term_id = x2 JOIN langs a ON a.path = p.path JOIN langs b ON b.path = q.path), s AS (SELECT p1 AS path, x1, x2, v * w / t AS v FROM (SELECT *, sum(w) OVER (PARTITION BY x1, x2) AS t FROM j) WHERE p1 = p2), n AS (SELECT path, sum(v * CASE WHEN x1 = x2 THEN 1 ELSE 2 END) AS n FROM s GROUP BY path) SELECT path, x1, x2, {r6_sql('v / n', 1e4)} AS e2 FROM s JOIN n USING (path)")
def pair_posterior_moments(spark: SparkSession, sf: str) -> DataFrame:
    """Each language's second moment from the root's, by the posterior of the pair, as joins of edges with words."""
    _, bags, v = prepared(spark, sf, PAIRED)
    _, _, nodes, words = lang_topics(spark, sf, PAIRED)
    edges = M.second_moment(bags, v).select("x1", "x2", "v")
    known = F.broadcast(words.join(F.broadcast(nodes.select("path", "alpha")), "path"))
    p, q = known.toDF("p1", "x1", "f1", "a1"), known.toDF("p2", "x2", "f2", "a2")
    joint = edges.join(p, "x1").join(q, "x2").withColumn("w", F.col("f1") * F.col("f2") * F.col("a1") * (F.col("a2") + (F.col("p1") == F.col("p2")).cast("int")))
    total = joint.groupBy("x1", "x2").agg(F.sum("w").alias("t"))
    own = joint.where("p1 = p2").join(total, ["x1", "x2"]).select(F.col("p1").alias("path"), "x1", "x2", (F.col("v") * F.col("w") / F.col("t")).alias("v"))
    norm = own.groupBy("path").agg(F.sum(F.col("v") * F.when(F.col("x1") == F.col("x2"), 1).otherwise(2)).alias("n"))
    return own.join(F.broadcast(norm), "path").select("path", "x1", "x2", r6(F.col("v") / F.col("n"), 1e4).alias("e2"))


@query(f"WITH {bags_sql(TOP)}, {LANG_SQL}, g AS (SELECT p.path, t.term_id FROM langs p CROSS JOIN (SELECT DISTINCT term_id FROM phi) t), f AS (SELECT path, term_id, coalesce(phi, 0) + 1e-12 AS phi FROM g LEFT JOIN phi USING (path, term_id)), n AS (SELECT path, term_id, phi / sum(phi) OVER (PARTITION BY path) AS phi FROM f) SELECT a.path AS a, b.path AS b, {r6_sql('sum(a.phi * ln(a.phi / b.phi))')} AS kl FROM n a JOIN n b USING (term_id) GROUP BY ALL")
def kl_matrix(spark: SparkSession, sf: str) -> DataFrame:
    _, _, _, words = lang_topics(spark, sf, TOP)
    return measures.kl_matrix(words).select("a", "b", r6("kl").alias("kl"))


@query(f"WITH {bags_sql(PAIRED)}, n AS (SELECT CAST(count(*) AS DOUBLE) AS n FROM documents), s AS (SELECT term_id, count(*) AS n1 FROM lb GROUP BY term_id), p AS (SELECT a.term_id AS x1, b.term_id AS x2, count(*) AS c FROM lb a JOIN lb b ON a.doc_id = b.doc_id AND a.term_id < b.term_id GROUP BY ALL) SELECT x1, x2, {r6_sql('CASE WHEN c / n >= 1 THEN 1.0 ELSE ln((c / n) / (u.n1 / n * w.n1 / n)) / -ln(c / n) END')} AS npmi FROM p JOIN s u ON u.term_id = x1 JOIN s w ON w.term_id = x2 CROSS JOIN n")
def npmi_pairs(spark: SparkSession, sf: str) -> DataFrame:
    _, long = long_prepared(spark, sf, PAIRED)
    n = tables.read_table(spark, sf, "documents").count()
    return measures.npmi_pairs(long, n).select("x1", "x2", r6("npmi").alias("npmi"))


@query("WITH t AS (SELECT source AS cluster, lang AS truth, CAST(count(*) AS DOUBLE) AS n FROM documents GROUP BY ALL), s AS (SELECT sum(n) AS t FROM t), r AS (SELECT cluster, sum(n) AS a, max(n) AS top FROM t GROUP BY 1), c AS (SELECT truth, sum(n) AS b FROM t GROUP BY 1), mi AS (SELECT sum(n / s.t * ln(n * s.t / (a * b))) AS mi FROM t JOIN r USING (cluster) JOIN c USING (truth) CROSS JOIN s), ha AS (SELECT sum(-a / t * ln(a / t)) AS ha FROM r CROSS JOIN s), hb AS (SELECT sum(-b / t * ln(b / t)) AS hb FROM c CROSS JOIN s) SELECT round((SELECT sum(top) FROM r) / (SELECT t FROM s), 6) AS purity, round(2 * mi / (ha + hb), 6) AS nmi FROM mi CROSS JOIN ha CROSS JOIN hb")
def purity_nmi(spark: SparkSession, sf: str) -> DataFrame:
    found = measures.purity_nmi(tables.read_table(spark, sf, "documents"), "source", "lang")
    return found.select(F.round("purity", 6).alias("purity"), F.round("nmi", 6).alias("nmi"))

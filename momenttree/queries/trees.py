"""Spectral, tree and baseline queries.  Their results are identities and facts that hold whatever the corpus."""

from __future__ import annotations

import uuid
from concurrent.futures import ThreadPoolExecutor

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from momenttree.baselines import gibbs, network
from momenttree.evaluation import intrusion, measures
from momenttree.evaluation.cost import Ledger
from momenttree.functions import paths
from momenttree.functions import tensor as X
from momenttree.operators import assign as A
from momenttree.operators import corpus as C
from momenttree.operators import moments as M
from momenttree.operators import phrases as P
from momenttree.operators import sampler
from momenttree.operators import tree as TT
from momenttree.plans import build as B
from momenttree.plans import select
from momenttree.queries import query
from momenttree.queries.shared import LANG_SQL, bags_sql, documents, lang_topics, long_prepared, r6, tokens
from momenttree.runtime import shared_dir, stored
from momenttree.sources import corpus_source, tables

V, MIN_DF, LANGS = 1_500, 20, 4
SMALL = 100


def spectral_bags(spark: SparkSession, sf: str, top: int = V, min_df: int = MIN_DF) -> tuple[DataFrame, DataFrame, int]:
    """vocabulary, bags (stored: every level scans them), size."""
    tok = stored(tokens(spark, sf), "tokens")
    vocab = stored(C.vocabulary(tok, min_df=min_df, top=top), "vocab")
    v = vocab.count()
    return vocab, stored(C.bags(tok, vocab, size=v), "bags"), v


def synthetic(spark: SparkSession, n: int = 3_000, v: int = 30, k: int = 3, length: int = 40, seed: int = 5) -> tuple[TT.TopicTree, DataFrame]:
    tree = sampler.sample_tree((k,), v, seed=seed)
    return tree, stored(sampler.as_bags(sampler.sample_corpus(spark, tree, n, length, seed=seed)), "synthetic")


def known_tree(spark: SparkSession, sf: str, top: int) -> TT.TopicTree:
    """The languages as topics of one level: shares of documents and of the words of a bounded vocabulary."""
    _, _, nodes, words = lang_topics(spark, sf, top)
    tree = TT.TopicTree({"o": TT.Node("o", np.zeros(top), status="inner")})
    for r in nodes.orderBy("path").collect():
        tree.nodes[r.path] = TT.Node(r.path, np.zeros(top), r.alpha)
    for r in words.collect():
        tree.nodes[r.path].phi[r.term_id] = r.phi
    return TT.mix_up_tree(tree)


def sources_below(spark: SparkSession, sf: str) -> DataFrame:
    """lang, source, parent (o/1: the languages in their order), path (o/1/2: the sources of a language in their order), n documents."""
    pairs = documents(spark, sf).where("lang is not null and source is not null").groupBy("lang", "source").agg(F.count("*").alias("n"))
    parent = F.concat(F.lit("o/"), F.dense_rank().over(Window.orderBy("lang")).cast("string"))  # a row for each pair
    numbered = pairs.withColumn("parent", parent).withColumn("j", F.row_number().over(Window.partitionBy("lang").orderBy("source")))
    return numbered.select("lang", "source", "parent", F.concat_ws("/", "parent", "j").alias("path"), "n")


def source_words(spark: SparkSession, sf: str, top: int) -> DataFrame:
    """term, parent, path, c: occurrences of each word of a bounded vocabulary under each source of a language."""
    vocab, long = long_prepared(spark, sf, top)
    by = documents(spark, sf).select("doc_id", "lang", "source").join(F.broadcast(sources_below(spark, sf)), ["lang", "source"]).select("doc_id", "parent", "path")
    return long.join(by, "doc_id").groupBy("term_id", "parent", "path").agg(F.sum("c").alias("c")).join(F.broadcast(vocab.select("term_id", "term")), "term_id").select("term_id", "term", "parent", "path", "c")


def source_tree(spark: SparkSession, sf: str, top: int) -> TT.TopicTree:
    """Languages, and below each its sources, as topics."""
    rows = sources_below(spark, sf).collect()
    total = {p: sum(r.n for r in rows if r.parent == p) for p in sorted({r.parent for r in rows})}
    tree = TT.TopicTree({"o": TT.Node("o", np.zeros(top), status="inner")} | {p: TT.Node(p, np.zeros(top), n / sum(total.values()), status="inner") for p, n in total.items()})
    tree.nodes |= {r.path: TT.Node(r.path, np.zeros(top), r.n / total[r.parent]) for r in rows}
    for r in source_words(spark, sf, top).collect():
        tree.nodes[r.path].phi[r.term_id] = r.c
    for r in rows:
        tree.nodes[r.path].phi /= max(tree.nodes[r.path].phi.sum(), 1)
    return TT.mix_up_tree(tree)


def own_words(spark: SparkSession, sf: str, n: int = 12, top: int = 5_000) -> dict[str, list[str]]:
    """Topic -> its n most frequent own words, for languages and their sources.

    A word is its most frequent language's own and, below it, that of the source in whose words it has the largest share.
    """
    words = source_words(spark, sf, top)
    langs = words.groupBy("term", F.col("parent").alias("path")).agg(F.sum("c").alias("c")).withColumn("score", F.col("c").cast("double"))
    first = Window.partitionBy("term").orderBy(F.col("score").desc(), "path")
    langs = langs.withColumn("place", F.row_number().over(first)).where("place = 1").select("term", "path", "c")
    share = words.withColumn("score", F.col("c") / F.sum("c").over(Window.partitionBy("path"))).join(langs.select("term", F.col("path").alias("parent")), ["term", "parent"])
    below = share.withColumn("place", F.row_number().over(first)).where("place = 1").select("term", "path", "c")
    rank = F.row_number().over(Window.partitionBy("path").orderBy(F.col("c").desc(), "term"))
    out: dict[str, list[str]] = {}
    for r in sorted(langs.union(below).withColumn("rank", rank).where(F.col("rank") <= n).collect(), key=lambda r: (r.path, r["rank"])):
        out.setdefault(r.path, []).append(r.term)
    return {p: own for p, own in out.items() if len(own) >= 5}


def _rows(spark: SparkSession, rows: list[tuple], ddl: str) -> DataFrame:
    return spark.createDataFrame(rows, ddl)


def topic_top_words(spark: SparkSession, sf: str, k: int = LANGS) -> DataFrame:
    """path, rank, term, phi of a flat decomposition."""
    vocab, bags, v = spectral_bags(spark, sf)
    tree = B.build_tree(bags, v, width=k, height=1)
    words = tree.words_df(spark, 1e-12).where("path <> 'o'").join(F.broadcast(vocab.select("term_id", "term")), "term_id")
    ranked = words.withColumn("rank", F.row_number().over(Window.partitionBy("path").orderBy(F.col("phi").desc(), "term")))
    return ranked.where("rank <= 10").select("path", "rank", "term", r6("phi").alias("phi"))


@query("SELECT CAST(i AS INT) AS i, CAST(j AS INT) AS j, CASE WHEN i = j THEN 1.0 ELSE 0.0 END AS value FROM range(4) a(i), range(4) b(j)")
def whitening_identity(spark: SparkSession, sf: str) -> DataFrame:
    """W' M2 W on the whole corpus."""
    _, bags, v = spectral_bags(spark, sf)
    root = M.moments_of(bags, v)["o"]
    sigma, u = X.largest_eigs(root.e2, LANGS)
    w = X.lean_whitener(u, sigma, root.m1, 0.1).w
    m2 = 1.1 * (u * sigma) @ u.T - 0.1 * np.outer(u @ (u.T @ root.m1), u @ (u.T @ root.m1))
    got = w.T @ m2 @ w
    return _rows(spark, [(i, j, float(round(got[i, j], 6) + 0.0)) for i in range(LANGS) for j in range(LANGS)], "i int, j int, value double")


@query("SELECT 0.0 AS gap")
def u_identity(spark: SparkSession, sf: str) -> DataFrame:
    """The terms of E2 and M1 by the direct sum and by the identity of whitening."""
    _, bags, v = spectral_bags(spark, sf)
    root = M.moments_of(bags, v)["o"]
    sigma, u = X.largest_eigs(root.e2, LANGS)
    w = X.lean_whitener(u, sigma, u @ (u.T @ root.m1), 0.1).w
    direct, quick = X.u_terms(w, root.m1, 0.1, root.e2), X.u_terms(w, root.m1, 0.1)
    return _rows(spark, [(float(round(np.abs(direct - quick).max(), 6) + 0.0),)], "gap double")


@query("SELECT 0.0 AS asymmetry")
def core_symmetry(spark: SparkSession, sf: str) -> DataFrame:
    """The projected third moment is symmetric before it is made so."""
    _, bags, v = spectral_bags(spark, sf)
    root = M.moments_of(bags, v)["o"]
    sigma, u = X.largest_eigs(root.e2, LANGS)
    w = X.lean_whitener(u, sigma, root.m1, 0.1).w
    p = M.project_third(bags, v, {"o": w})["o"]
    t = p.p1 - X.three_ways(p.p2) + 2 * np.einsum("x,xi,xj,xl->ijl", p.g, w, w, w, optimize=True)
    gap = max(np.abs(t - np.transpose(t, o)).max() for o in ((0, 2, 1), (1, 0, 2), (2, 1, 0))) / np.abs(t).max()
    return _rows(spark, [(float(round(gap, 6) + 0.0),)], "asymmetry double")


@query("SELECT v AS variant, 0.0 AS gap FROM (VALUES ('lean-dense_m3'), ('dense_m2-dense'), ('lean-scan_power'), ('explicit-implicit')) t(v)")
def variants_agree(spark: SparkSession, sf: str) -> DataFrame:
    """Variants that share a whitener give the same words; engines agree."""
    _, bags, v = spectral_bags(spark, sf, SMALL, 1)
    flat = {x: B.decompose(bags, v, 3, variant=x) for x in ("lean", "dense_m3", "dense_m2", "dense")}
    flat["scan_power"] = B.decompose(bags, v, 3, variant="scan_power", starts=8, steps=8)
    flat["explicit"], flat["implicit"] = flat["lean"], B.decompose(bags, v, 3, engine="implicit", sweeps=60)
    rows = [(f"{a}-{b}", float(round(np.abs(flat[a].phi - flat[b].phi).max(), 4) + 0.0)) for a, b in (("lean", "dense_m3"), ("dense_m2", "dense"), ("lean", "scan_power"), ("explicit", "implicit"))]
    return _rows(spark, rows, "variant string, gap double")


@query(f"WITH {bags_sql(SMALL)}, {LANG_SQL} SELECT CAST(row_number() OVER (ORDER BY lang) AS INT) AS component, round(CAST(alpha AS DOUBLE), 6) AS alpha, 0.0 AS error FROM langs")
def exact_recovery(spark: SparkSession, sf: str) -> DataFrame:
    """Exact moments of the languages as topics give their shares and words back."""
    truth = known_tree(spark, sf, SMALL)
    own = truth.children("o")
    alpha, phi = np.array([truth.nodes[c].alpha for c in own]), np.stack([truth.nodes[c].phi for c in own], axis=1)
    m1, e2, e3 = (X.population_moments(alpha, phi, k) for k in (1, 2, 3))
    m2, m3 = X.centred_moments(m1, e2, e3, 1.0)
    values, vectors = X.largest_eigs(m2, len(own))
    w = X.whiten(vectors, values)
    flat = X.recover(X.power_decompose(X.multilinear(m3, w.w, w.w, w.w), seed=1), w, 1.0)
    found = X.best_matching(np.array([[np.abs(flat.phi[:, j] - phi[:, i]).sum() for j in range(len(own))] for i in range(len(own))]))
    return _rows(spark, [(i + 1, float(round(flat.alpha[j], 6)), float(round(np.abs(flat.phi[:, j] - phi[:, i]).sum(), 6) + 0.0)) for i, j in enumerate(found)], "component int, alpha double, error double")


@query("SELECT true AS close, 1.0 AS share_sum")
def sampled_recovery(spark: SparkSession, sf: str) -> DataFrame:
    """A sampled corpus of a known tree."""
    truth, bags = synthetic(spark)
    flat = B.decompose(bags, 30, 3, alpha0=3.0)
    tree = TT.TopicTree({"o": TT.Node("o", np.zeros(30))} | {f"o/{z + 1}": TT.Node(f"o/{z + 1}", flat.phi[:, z], float(flat.alpha[z])) for z in range(3)})
    worst = max(e for e, _ in measures.recovery_error(tree, truth).values())
    return _rows(spark, [(bool(worst < 0.3), float(round(flat.share_sum, 0)))], "close boolean, share_sum double")


@query("SELECT lang, true AS own_topic FROM documents WHERE lang IS NOT NULL GROUP BY lang")
def lang_recovery(spark: SparkSession, sf: str) -> DataFrame:
    """Each language has a topic of its own: the hard topic of most of its documents, shared with no other language."""
    _, bags, v = spectral_bags(spark, sf)
    tree = B.build_tree(bags, v, width=LANGS, height=1)
    long = bags.select("doc_id", F.explode(F.arrays_zip("terms", "counts")).alias("t")).select("doc_id", F.col("t.terms").alias("term_id"), F.col("t.counts").alias("c"))
    hard = A.assign(long, A.weights_df(spark, tree), mode="hard").join(documents(spark, sf).select("doc_id", "lang"), "doc_id")
    counted = hard.groupBy("lang", "path").agg(F.count("*").alias("n"))
    top = counted.groupBy("lang").agg(F.max_by("path", "n").alias("path"), (F.max("n") / F.sum("n")).alias("share"))
    users = top.groupBy("path").agg(F.count("*").alias("users"))
    return top.join(users, "path").select("lang", ((F.col("users") == 1) & (F.col("share") > 0.9)).alias("own_topic"))


def _tree(spark: SparkSession, sf: str, **settings) -> tuple[DataFrame, DataFrame, int, TT.TopicTree]:
    vocab, bags, v = spectral_bags(spark, sf)
    return vocab, bags, v, B.build_tree(bags, v, **({"width": LANGS, "height": 2} | settings))


@query()
def topic_tree(spark: SparkSession, sf: str) -> DataFrame:
    return _tree(spark, sf)[3].nodes_df(spark).select("path", "parent", "suffix", "level", "n_children", r6("weight").alias("weight"), "status")


@query()
def describe_tree(spark: SparkSession, sf: str) -> DataFrame:
    """Words and, ranked under each parent, phrases of every node."""
    vocab, _, _, tree = _tree(spark, sf)
    words = tree.words_df(spark, 1e-12)
    named = words.join(F.broadcast(vocab.select("term_id", "term")), "term_id").select("path", "term", "phi")
    docs = documents(spark, sf)
    ranked = P.rank_tree(P.by_document(docs), tree.nodes_df(spark), named, docs.count(), min_support=40, top=10)
    return TT.describe(words, vocab, ranked=ranked)


@query("SELECT * FROM (VALUES (0, true), (1, true), (2, true)) t(level, bounded)")
def tree_bounds(spark: SparkSession, sf: str) -> DataFrame:
    nodes = _tree(spark, sf)[3].nodes_df(spark)
    return nodes.groupBy(paths.level(F.col("path")).alias("level")).agg(F.count("*").alias("n")).select("level", (F.col("n") <= F.pow(F.lit(LANGS), F.col("level"))).alias("bounded"))


@query("SELECT true AS all_sum_to_one, 0 AS negative")
def phi_is_distribution(spark: SparkSession, sf: str) -> DataFrame:
    words = _tree(spark, sf)[3].words_df(spark, -1.0)
    sums = words.groupBy("path").agg(F.sum("phi").alias("s"), F.min("phi").alias("least"))
    return sums.agg(F.bool_and(F.abs(F.col("s") - 1) < 1e-9).alias("all_sum_to_one"), F.sum((F.col("least") < 0).cast("int")).cast("int").alias("negative"))


@query("SELECT 0 AS changed, 3 AS children")
def revise_branch(spark: SparkSession, sf: str) -> DataFrame:
    """The first topic with three children instead of four: rows changed outside its subtree."""
    _, bags, v, tree = _tree(spark, sf)
    after = B.revise(tree, bags, "o/1", n_children=3, width=LANGS)
    outside = ~paths.is_below(F.col("path"), "o/1")
    a, b = (t.words_df(spark).where(outside) for t in (tree, after))
    changed = a.exceptAll(b).union(b.exceptAll(a)).agg(F.count("*").cast("int").alias("changed"))
    return changed.withColumn("children", F.lit(len(after.children("o/1"))))


@query("SELECT true AS subsumed")
def subsumed(spark: SparkSession, sf: str) -> DataFrame:
    """The flat tree is part of the deeper one."""
    _, bags, v, deep = _tree(spark, sf)
    shallow = B.build_tree(bags, v, width=LANGS, height=1)
    return TT.is_subsumed(shallow.words_df(spark), deep.words_df(spark))


_SOURCES_SQL = "pairs AS (SELECT DISTINCT lang, source FROM documents WHERE lang IS NOT NULL AND source IS NOT NULL), below AS (SELECT 'o/' || CAST(dense_rank() OVER (ORDER BY lang) AS VARCHAR) AS parent, CAST(row_number() OVER (PARTITION BY lang ORDER BY source) AS VARCHAR) AS j FROM pairs)"


@query(f"WITH {_SOURCES_SQL} SELECT 'o' AS path UNION ALL SELECT DISTINCT parent FROM below UNION ALL SELECT parent || '/' || j FROM below WHERE parent <> 'o/1'")
def collapse_prune(spark: SparkSession, sf: str) -> DataFrame:
    """Languages and their sources as a tree; the first language's sources are cut."""
    return TT.collapse(source_tree(spark, sf, SMALL), ["o/1"]).nodes_df(spark).select("path")


@query("SELECT 4 AS width, true AS in_grid")
def suggest(spark: SparkSession, sf: str) -> DataFrame:
    _, bags, v = spectral_bags(spark, sf)
    root = M.moments_of(bags, v)["o"]
    width = select.suggest_width(X.largest_eigs(root.e2, 8)[0])
    alpha0, rows = select.suggest_alpha0(bags, v, width)
    return _rows(spark, [(width, alpha0 in [r[0] for r in rows])], "width int, in_grid boolean")


@query("SELECT true AS same_nodes, 0.0 AS gap")
def tree_round_trip(spark: SparkSession, sf: str) -> DataFrame:
    tree = sampler.sample_tree((2, 3), 40, seed=2)
    where = f"{shared_dir(spark).rstrip('/')}/saved_tree_{uuid.uuid4().hex}"
    TT.save_tree(tree, spark, where)
    again = TT.load_tree(spark, where)
    return _rows(spark, [(sorted(tree.nodes) == sorted(again.nodes), float(max(np.abs(tree.nodes[p].phi - again.nodes[p].phi).max() for p in tree.nodes)))], "same_nodes boolean, gap double")


@query(f"WITH {bags_sql(SMALL)}, {LANG_SQL} SELECT CAST(row_number() OVER (ORDER BY lang) - 1 AS INT) AS row, CAST(row_number() OVER (ORDER BY lang DESC) - 1 AS INT) AS matched FROM langs")
def topic_matching(spark: SparkSession, sf: str) -> DataFrame:
    """The languages as topics matched with themselves in the opposite order."""
    tree = known_tree(spark, sf, SMALL)
    own = [tree.nodes[c].phi for c in tree.children("o")]
    cost = np.array([[X.kl(a, b) for b in reversed(own)] for a in own])
    return _rows(spark, [(i, int(j)) for i, j in enumerate(X.best_matching(cost))], "row int, matched int")


@query("SELECT true AS lean_is_steadier")
def run_variance(spark: SparkSession, sf: str) -> DataFrame:
    """Variance over runs with different seeds: moments against the network EM and Gibbs, each to its end: EM until it rises no more, Gibbs all its sweeps."""
    _, bags, v = spectral_bags(spark, sf)
    runs = 10
    lean = measures.variance([B.build_tree(bags, v, width=3, height=1, seed=s) for s in range(runs)])
    edges = stored(M.second_moment(bags, v).select("x1", "x2", (F.col("v") * 1e6).alias("w")).where("w > 0"), "edges")
    with ThreadPoolExecutor(4) as pool:  # the driver only waits for small jobs
        chains = pool.submit(gibbs.recursive_lda_runs, bags, v, widths=(3,), seeds=range(runs))
        em = measures.variance(list(pool.map(lambda s: network.pair_network_em(edges, v, widths=(3,), seed=s), range(runs))))
        lda = measures.variance(chains.result())
    return _rows(spark, [(bool(lean < em and lean < lda),)], "lean_is_steadier boolean")


@query("SELECT 'phrase' AS kind, 200 AS n, 200 AS one_intruder UNION ALL SELECT 'topic', 160, 160")
def intrusion_questions(spark: SparkSession, sf: str) -> DataFrame:
    """Questions about the own words of languages and of their sources."""
    ranked = own_words(spark, sf)
    phrase, topic = intrusion.phrase_intrusion(ranked, 200), intrusion.topic_intrusion(ranked, 160)
    ok = sum(q["options"][q["intruder"]] not in ranked[q["topic"]] and sum(o in ranked[q["topic"]] for o in q["options"]) == 3 for q in phrase)
    names = {"; ".join(p[:5]): k for k, p in sorted(ranked.items(), key=lambda x: paths.level_of(x[0]))}
    ok2 = sum(sum(paths.parent_of(names[o]) == q["topic"] for o in q["options"]) == 3 and paths.parent_of(names[q["options"][q["intruder"]]]) != q["topic"] for q in topic if q["topic"] != "o") + sum(q["topic"] == "o" for q in topic)
    return _rows(spark, [("phrase", len(phrase), ok), ("topic", len(topic), ok2)], "kind string, n int, one_intruder int")


@query("SELECT 0.75 AS precision, 0.6 AS recall, round(2 * 0.75 * 0.6 / 1.35, 6) AS f1")
def intrusion_f1(spark: SparkSession, sf: str) -> DataFrame:
    """Questions about the own words of languages and sources, three judges who know these words: of every five questions all
    find the intruder in three, answer one wrong and make no choice in one."""
    ranked = own_words(spark, sf)
    questions = intrusion.phrase_intrusion(ranked, 200)
    right = [next(i for i, o in enumerate(q["options"]) if o not in ranked[q["topic"]]) for q in questions]
    judges = [[None if k % 5 == 4 else (x + (k % 5 == 3)) % 4 for k, x in enumerate(right)] for _ in range(3)]
    s = intrusion.score_intrusion(questions, judges)
    return _rows(spark, [(s["precision"], s["recall"], round(s["f1"], 6))], "precision double, recall double, f1 double")


@query("SELECT CAST(count(*) AS INT) AS n, CAST(40 * count(*) AS INT) AS tokens, CAST(0 AS INT) AS foreign FROM documents")
def corpus_source_rows(spark: SparkSession, sf: str) -> DataFrame:
    """A synthetic text for each document, drawn from the languages as topics; foreign: words that no language has."""
    corpus_source.register(spark)
    tree, n = known_tree(spark, sf, 50), documents(spark, sf).count()
    read = spark.read.format("topic_corpus").option("docs", n).option("length", 40).option("partitions", max(4, n // 5_000))
    words = F.split("text", " ")
    known = F.array(*(F.lit(f"w{x}") for x in np.flatnonzero(sum(tree.nodes[p].phi for p in tree.children("o")))))
    rows = read.option("tree", corpus_source.tree_option(tree)).load()
    return rows.agg(F.count("*").cast("int").alias("n"), F.coalesce(F.sum(F.size(words)), F.lit(0)).cast("int").alias("tokens"), F.coalesce(F.sum(F.size(F.array_except(words, known))), F.lit(0)).cast("int").alias("foreign"))


@query("SELECT 4 AS nodes, true AS sums_to_one")
def baseline_recursive_lda(spark: SparkSession, sf: str) -> DataFrame:
    _, bags, v = spectral_bags(spark, sf, 200, 1)
    tree = gibbs.recursive_lda(bags, v, widths=(3,), iters=3)
    return _rows(spark, [(len(tree.nodes), bool(all(abs(n.phi.sum() - 1) < 1e-9 for n in tree.nodes.values())))], "nodes int, sums_to_one boolean")


@query("SELECT 4 AS nodes, true AS sums_to_one")
def baseline_recursive_lda_variational(spark: SparkSession, sf: str) -> DataFrame:
    _, bags, v = spectral_bags(spark, sf, 200, 1)
    tree = gibbs.recursive_lda(bags, v, widths=(3,), iters=5, engine="variational")
    return _rows(spark, [(len(tree.nodes), bool(all(abs(n.phi.sum() - 1) < 1e-9 for n in tree.nodes.values())))], "nodes int, sums_to_one boolean")


@query("SELECT true AS never_falls, 0.0 AS split_gap, 10 AS nodes")
def baseline_pair_network(spark: SparkSession, sf: str) -> DataFrame:
    _, bags, v = spectral_bags(spark, sf, 200, 1)
    edges = stored(M.second_moment(bags, v).select("x1", "x2", (F.col("v") * 1e6).alias("w")).where("w > 0"), "edges")
    fit = network.cluster(edges, v, 3, iters=8)
    rising = bool(all(b >= a - 1e-6 * abs(a) for a, b in zip(fit.likelihood, fit.likelihood[1:], strict=False)))
    parts = network.split_edges(edges, fit).groupBy("x1", "x2").agg(F.sum("w").alias("s"))
    gap = edges.join(parts, ["x1", "x2"]).agg(F.max(F.abs(F.col("s") - F.col("w")) / F.col("w"))).first()[0]
    tree = network.pair_network_em(edges, v, widths=(3, 2), iters=4)
    return _rows(spark, [(rising, float(round(gap, 9) + 0.0), len(tree.nodes))], "never_falls boolean, split_gap double, nodes int")


@query("SELECT 1 + 2 + 4 AS nodes, true AS tokens_kept, 7 AS tree_nodes")
def baseline_supertopic(spark: SparkSession, sf: str) -> DataFrame:
    _, bags, v = spectral_bags(spark, sf, SMALL, 1)
    model = gibbs.supertopic_gibbs(bags, v, n_super=2, n_sub=4, iters=2)
    tokens_ = bags.agg(F.sum("len")).first()[0]
    tree = gibbs.strongest_subtopics(model, 2)
    return _rows(spark, [(1 + model.phi_super.shape[1] + model.phi_sub.shape[1], bool(model.tokens == tokens_), len(tree.nodes))], "nodes int, tokens_kept boolean, tree_nodes int")


@query("SELECT true AS one_path_each, 2 AS height, CAST(count(DISTINCT s_nationkey) AS INT) AS docs FROM supplier WHERE s_nationkey IS NOT NULL AND s_acctbal IS NOT NULL")
def baseline_nested_partition(spark: SparkSession, sf: str) -> DataFrame:
    """Nations as documents whose words are the balances of their suppliers in steps of 500: the sampler is sequential, and nations stay few."""
    tok = stored(tables.nation_docs(spark, sf), "nations")
    vocab = stored(C.vocabulary(tok, top=1_000), "vocab")
    v = vocab.count()
    bags = stored(C.bags(tok, vocab, min_len=1, size=v), "nested")
    tree, leaf = gibbs.nested_partition_gibbs(bags, v, height=2, iters=3)
    one_each = tok.count() == len(leaf) and all(p in tree.nodes and paths.level_of(p) == 2 for p in leaf.values())
    return _rows(spark, [(bool(one_each), tree.height(), len(leaf))], "one_path_each boolean, height int, docs int")


@query("SELECT true AS agrees, true AS scans_grow")
def baseline_scan_power(spark: SparkSession, sf: str) -> DataFrame:
    """Power iteration by rescanning: the same shares, many more scans."""
    _, bags, v = spectral_bags(spark, sf, SMALL, 1)
    few, many = Ledger(), Ledger()
    a = B.decompose(bags, v, 3, few, starts=8, steps=8)
    b = B.decompose(bags, v, 3, many, variant="scan_power", starts=8, steps=8)
    return _rows(spark, [(bool(np.abs(a.shares - b.shares).max() < 1e-4), bool(few.scans == 2 and many.scans == 1 + 3 * 9))], "agrees boolean, scans_grow boolean")


@query("SELECT 4 AS scans, 512 AS core_bytes, true AS sparse")
def cost_ledger(spark: SparkSession, sf: str) -> DataFrame:
    """Two scans a level, whatever the number of nodes."""
    ledger = Ledger()
    _, bags, v = spectral_bags(spark, sf)
    B.build_tree(bags, v, ledger, width=LANGS, height=2)
    return _rows(spark, [(ledger.scans, ledger.bytes_of(v, 4)["core"], bool(ledger.nonzeros < v * v))], "scans int, core_bytes int, sparse boolean")

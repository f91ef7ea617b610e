"""Robustness, recovery, purity."""

from __future__ import annotations

import itertools

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from momenttree.functions import paths
from momenttree.functions.tensor import best_matching, kl
from momenttree.operators.tree import TopicTree, match_topics


def variance(runs: list[TopicTree], eps: float = 1e-12) -> float:
    """Mean divergence between matched topics over all ordered pairs of runs, the root left out."""
    values = []
    for a, b in itertools.permutations(runs, 2):
        matched = {p: q for p, q in match_topics(a, b, eps).items() if p != paths.ROOT}
        values.append(np.mean([kl(a.nodes[p].phi, b.nodes[q].phi, eps) for p, q in matched.items()]) if matched else 0.0)
    return float(np.mean(values)) if values else 0.0


def recovery_error(tree: TopicTree, truth: TopicTree) -> dict[str, tuple[float, float]]:
    """Node of the truth -> (L1 error of words, absolute error of its share among its siblings), matched top down at least L1."""
    found, out, todo = {paths.ROOT: paths.ROOT}, {}, [paths.ROOT]
    while todo:
        here = todo.pop()
        want, got = truth.children(here), tree.children(found[here])
        if not want or not got:
            continue
        cost = np.array([[np.abs(truth.nodes[p].phi - tree.nodes[q].phi).sum() for q in got] for p in want])
        share = lambda t, own: np.array([t.nodes[c].alpha for c in own]) / sum(t.nodes[c].alpha for c in own)
        a, b = share(truth, want), share(tree, got)
        for i, c in enumerate(best_matching(cost)):
            if c >= 0:
                found[want[i]] = got[c]
                out[want[i]] = float(cost[i, c]), float(abs(a[i] - b[c]))
                todo.append(want[i])
    return out


def revision_delta(before: TopicTree, after: TopicTree, path: str) -> float:
    """Largest change of any word probability outside the subtree of path; path itself is outside."""
    rest = [p for p in before.nodes if not p.startswith(path + "/")]
    return max((float(np.abs(before.nodes[p].phi - after.nodes[p].phi).max()) if p in after.nodes else float("inf") for p in rest), default=0.0)


def contingency(pairs: DataFrame, cluster: str, truth: str) -> DataFrame:
    return pairs.groupBy(F.col(cluster).alias("cluster"), F.col(truth).alias("truth")).agg(F.count("*").alias("n"))


def purity_nmi(pairs: DataFrame, cluster: str, truth: str) -> DataFrame:
    """One row: purity, nmi (mutual information over the mean of the entropies, natural logarithm)."""
    table = contingency(pairs, cluster, truth)
    total = table.agg(F.sum("n").alias("t"))
    rows, cols = table.groupBy("cluster").agg(F.sum("n").alias("a"), F.max("n").alias("top")), table.groupBy("truth").agg(F.sum("n").alias("b"))
    joined = table.join(rows, "cluster").join(cols, "truth").crossJoin(F.broadcast(total))
    mutual = joined.agg(F.sum(F.col("n") / F.col("t") * F.log(F.col("n") * F.col("t") / (F.col("a") * F.col("b")))).alias("mi"))
    entropy = lambda df, c: df.crossJoin(F.broadcast(total)).agg(F.sum(-F.col(c) / F.col("t") * F.log(F.col(c) / F.col("t"))).alias("h"))
    pure = rows.crossJoin(F.broadcast(total)).agg((F.sum("top") / F.max("t")).alias("purity"))
    both = entropy(rows, "a").withColumnRenamed("h", "ha").crossJoin(entropy(cols, "b").withColumnRenamed("h", "hb"))
    return pure.crossJoin(mutual).crossJoin(both).select("purity", F.when(F.col("ha") + F.col("hb") > 0, 2 * F.col("mi") / (F.col("ha") + F.col("hb"))).otherwise(1.0).alias("nmi"))


def npmi_pairs(long_bags: DataFrame, n_docs: int) -> DataFrame:
    """x1 < x2, both, npmi of words by the documents that hold them: for small vocabularies."""
    ids = long_bags.select("doc_id", "term_id").distinct()
    single = ids.groupBy("term_id").agg(F.count("*").alias("n"))
    pairs = ids.toDF("doc_id", "x1").join(ids.toDF("doc_id", "x2"), "doc_id").where("x1 < x2").groupBy("x1", "x2").agg(F.count("*").alias("both"))
    joined = pairs.join(F.broadcast(single.toDF("x1", "n1")), "x1").join(F.broadcast(single.toDF("x2", "n2")), "x2")
    p = F.col("both") / F.lit(float(n_docs))
    pmi = F.log(p / (F.col("n1") / F.lit(float(n_docs)) * F.col("n2") / F.lit(float(n_docs))))
    return joined.select("x1", "x2", "both", F.when(p >= 1, 1.0).otherwise(pmi / -F.log(p)).alias("npmi"))


def kl_matrix(words: DataFrame, eps: float = 1e-12) -> DataFrame:
    """a, b, kl over all ordered pairs of topics: topics are few, words are joined by id."""
    topics, terms = words.select("path").distinct(), words.select("term_id").distinct()
    full = topics.crossJoin(F.broadcast(terms)).join(words, ["path", "term_id"], "left").select("path", "term_id", (F.coalesce("phi", F.lit(0.0)) + eps).alias("phi"))
    norm = full.groupBy("path").agg(F.sum("phi").alias("s"))
    full = full.join(F.broadcast(norm), "path").select("path", "term_id", (F.col("phi") / F.col("s")).alias("phi"))
    pairs = full.toDF("a", "term_id", "p").join(full.toDF("b", "term_id", "q"), "term_id")
    return pairs.groupBy("a", "b").agg(F.sum(F.col("p") * F.log(F.col("p") / F.col("q"))).alias("kl"))

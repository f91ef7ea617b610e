"""The topic tree: nodes on the driver (at most a few hundred), tables for everyone else."""

from __future__ import annotations

import json
from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from momenttree.functions import paths
from momenttree.functions.tensor import best_matching, kl

NODE = "path string, parent string, suffix int, level int, n_children int, alpha0 double, alpha double, weight double, status string"
WORD = "path string, term_id int, phi double"


@dataclass
class Node:
    """phi: word distribution; alpha: Dirichlet weight under its parent; alpha0: sum over its children; weight: share of the corpus."""

    path: str
    phi: np.ndarray
    alpha: float = 1.0
    alpha0: float | None = None
    weight: float = 1.0
    status: str = "leaf"
    clipped: float = 0.0


@dataclass
class TopicTree:
    nodes: dict[str, Node] = field(default_factory=dict)
    scans: int = 0

    @property
    def v(self) -> int:
        return len(next(iter(self.nodes.values())).phi)

    def children(self, path: str) -> list[str]:
        return sorted((p for p in self.nodes if paths.parent_of(p) == path), key=lambda p: int(p.rpartition("/")[2]))

    def below(self, path: str) -> list[str]:
        return [p for p in self.nodes if p.startswith(path + "/")]

    def leaves(self) -> list[str]:
        return [p for p in self.nodes if not self.children(p)]

    def height(self) -> int:
        return max(map(paths.level_of, self.nodes))

    def level(self, k: int) -> list[str]:
        return [p for p in self.nodes if paths.level_of(p) == k]

    def copy(self) -> TopicTree:
        return TopicTree({p: replace(n) for p, n in self.nodes.items()}, self.scans)

    def nodes_df(self, spark: SparkSession) -> DataFrame:
        rows = [(p, paths.parent_of(p), int(p.rpartition("/")[2]) if "/" in p else None, paths.level_of(p), len(self.children(p)), n.alpha0, float(n.alpha), float(n.weight), n.status) for p, n in self.nodes.items()]
        return spark.createDataFrame(rows, NODE)

    def words_df(self, spark: SparkSession, least: float = 0.0) -> DataFrame:
        parts = [pd.DataFrame({"path": p, "term_id": np.flatnonzero(n.phi > least).astype(np.int32), "phi": n.phi[n.phi > least]}) for p, n in self.nodes.items()]
        return spark.createDataFrame(pd.concat(parts), WORD)


def save_tree(tree: TopicTree, spark: SparkSession, path: str) -> None:
    """Nodes, and words partitioned by level."""
    tree.nodes_df(spark).write.mode("overwrite").parquet(f"{path}/nodes")
    tree.words_df(spark).withColumn("level", paths.level(F.col("path"))).write.mode("overwrite").partitionBy("level").parquet(f"{path}/words")
    spark.createDataFrame([(json.dumps({"v": tree.v}),)], "meta string").write.mode("overwrite").text(f"{path}/meta")


def load_tree(spark: SparkSession, path: str) -> TopicTree:
    v = json.loads(spark.read.text(f"{path}/meta").first()[0])["v"]
    nodes = {r.path: Node(r.path, np.zeros(v), r.alpha, r.alpha0, r.weight, r.status) for r in spark.read.parquet(f"{path}/nodes").collect()}
    for p, own in spark.read.parquet(f"{path}/words").select("path", "term_id", "phi").toPandas().groupby("path"):
        nodes[p].phi[own["term_id"].to_numpy()] = own["phi"].to_numpy()
    return TopicTree(dict(sorted(nodes.items())))


def mix_up(nodes: DataFrame, words: DataFrame, height: int) -> DataFrame:
    """path, term_id, phi of every node from the leaves' words: a parent is the alpha-weighted mixture of its children."""
    level = paths.level(F.col("path"))
    parents = nodes.where("parent is not null").select("parent").distinct()
    out = words.join(parents.withColumnRenamed("parent", "path"), "path", "left_anti").select("path", "term_id", "phi")
    share = nodes.where("parent is not null").select("path", "parent", "alpha")
    totals = share.groupBy("parent").agg(F.sum("alpha").alias("total"))
    share = share.join(totals, "parent").select("path", "parent", (F.col("alpha") / F.col("total")).alias("share"))
    for k in range(height, 0, -1):
        made = out.where(level == k).join(F.broadcast(share), "path").groupBy("parent", "term_id").agg(F.sum(F.col("phi") * F.col("share")).alias("phi"))
        out = out.union(made.select(F.col("parent").alias("path"), "term_id", "phi"))
    return out


def mix_up_tree(tree: TopicTree) -> TopicTree:
    """The same on the driver."""
    out = tree.copy()
    for k in range(out.height() - 1, -1, -1):
        for p in out.level(k):
            own = out.children(p)
            if own:
                alpha = np.array([out.nodes[c].alpha for c in own])
                out.nodes[p].phi = np.stack([out.nodes[c].phi for c in own], axis=1) @ (alpha / alpha.sum())
    return out


def is_subsumed(small: DataFrame, large: DataFrame, tol: float = 1e-9) -> DataFrame:
    """One row, subsumed: whether every (path, term_id, phi) of small is in large within tol."""
    joined = small.alias("a").join(large.alias("b"), ["path", "term_id"], "full_outer").join(small.select("path").distinct(), "path", "left_semi")
    gap = F.abs(F.coalesce("a.phi", F.lit(0.0)) - F.coalesce("b.phi", F.lit(0.0)))
    return joined.agg(F.coalesce(F.bool_and(gap <= tol), F.lit(True)).alias("subsumed"))


def collapse(tree: TopicTree, nodes: list[str]) -> TopicTree:
    """Descendants of the named nodes cut; the nodes become leaves that keep their words."""
    out = tree.copy()
    for path in nodes:
        for below in out.below(path):
            del out.nodes[below]
        if path in out.nodes:
            out.nodes[path].status, out.nodes[path].alpha0 = "leaf", None
    return out


def match_topics(a: TopicTree, b: TopicTree, eps: float = 1e-12) -> dict[str, str]:
    """Nodes of a to nodes of b, top down: children of matched parents are matched at least total divergence."""
    found = {paths.ROOT: paths.ROOT}
    todo = [paths.ROOT]
    while todo:
        here = todo.pop()
        left, right = a.children(here), b.children(found[here])
        if not left or not right:
            continue
        cost = np.array([[kl(a.nodes[p].phi, b.nodes[q].phi, eps) for q in right] for p in left])
        for p, c in zip(left, best_matching(cost), strict=True):
            if c >= 0:
                found[p] = right[c]
                todo.append(p)
    return found


def describe(words: DataFrame, vocab: DataFrame, n: int = 10, ranked: DataFrame | None = None) -> DataFrame:
    """path, words and, with ranked phrases (path, rank, phrase), phrases: the best n of each node, best first."""
    from pyspark.sql import Window

    order = Window.partitionBy("path").orderBy(F.col("phi").desc(), "term")
    top = words.join(F.broadcast(vocab.select("term_id", "term")), "term_id").withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= n)
    out = top.groupBy("path").agg(F.array_sort(F.collect_list(F.struct("rank", "term"))).alias("w")).select("path", F.array_join(F.col("w.term"), " ").alias("words"))
    if ranked is None:
        return out
    best = ranked.where(F.col("rank") <= n).groupBy("path").agg(F.array_sort(F.collect_list(F.struct("rank", "phrase"))).alias("p")).select("path", F.array_join(F.col("p.phrase"), "; ").alias("phrases"))
    return out.join(best, "path", "left")

"""Synthetic corpora of a known tree."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from momenttree.functions import paths
from momenttree.functions.tensor import seed_of
from momenttree.operators.tree import Node, TopicTree, mix_up_tree
from momenttree.runtime import ship


def sample_tree(shape: tuple[int, ...], v: int, *, beta: float = 0.1, alpha: float = 1.0, seed: int = 0, disjoint: bool = False) -> TopicTree:
    """A full tree with shape[h] children at level h; leaf words from a Dirichlet, on disjoint ranges if asked."""
    random = np.random.default_rng(seed)
    tree = TopicTree({paths.ROOT: Node(paths.ROOT, np.zeros(v))})
    for h, k in enumerate(shape):
        for p in tree.level(h):
            tree.nodes[p].alpha0, tree.nodes[p].status = alpha * k, "inner"
            for z in range(k):
                tree.nodes[f"{p}/{z + 1}"] = Node(f"{p}/{z + 1}", np.zeros(v), alpha)
    leaves = tree.leaves()
    for n, p in enumerate(leaves):
        at = np.arange(n * v // len(leaves), (n + 1) * v // len(leaves)) if disjoint else np.arange(v)
        tree.nodes[p].phi[at] = random.dirichlet(np.full(len(at), beta))
    return mix_up_tree(tree)


def sample_corpus(spark: SparkSession, tree: TopicTree, n_docs: int, length: int, *, seed: int = 0, partitions: int = 8) -> DataFrame:
    """doc_id, terms (one for each token), leaves (the path of each token), theta (mixture over the root's children).

    Every document has its own seed, so the corpus does not depend on partitions.
    """
    ship(spark)
    children = {p: tree.children(p) for p in tree.nodes}
    sent = spark.sparkContext.broadcast((children, {p: np.array([tree.nodes[c].alpha for c in own]) for p, own in children.items()}, {p: tree.nodes[p].phi for p in tree.leaves()}))

    def draw(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        below, alpha, phi = sent.value
        for frame in frames:
            rows = []
            for doc in frame["id"]:
                random = np.random.default_rng(seed_of(seed, doc))
                theta = {p: random.dirichlet(a) for p, a in alpha.items() if len(a)}
                at = np.array([paths.ROOT] * length, dtype=object)
                while any(below[p] for p in set(at)):
                    for p in [p for p in dict.fromkeys(at) if below[p]]:
                        here = np.flatnonzero(at == p)
                        at[here] = np.array(below[p], dtype=object)[random.choice(len(below[p]), len(here), p=theta[p])]
                terms = np.empty(length, np.int32)
                for p in dict.fromkeys(at):
                    here = np.flatnonzero(at == p)
                    terms[here] = random.choice(len(phi[p]), len(here), p=phi[p])
                rows.append((int(doc), terms.tolist(), at.tolist(), theta[paths.ROOT].tolist()))
            yield pd.DataFrame(rows, columns=["doc_id", "terms", "leaves", "theta"])

    return spark.range(0, n_docs, 1, partitions).mapInPandas(draw, "doc_id bigint, terms array<int>, leaves array<string>, theta array<double>")


def as_bags(corpus: DataFrame) -> DataFrame:
    """Bags of a sampled corpus."""
    from pyspark.sql import functions as F

    words = corpus.select("doc_id", F.explode("terms").alias("term_id")).groupBy("doc_id", "term_id").agg(F.count("*").cast("double").alias("c"))
    pairs = F.array_sort(F.collect_list(F.struct("term_id", "c")))
    return words.groupBy("doc_id").agg(F.sum("c").alias("len"), pairs.alias("p")).select("doc_id", "len", F.col("p.term_id").alias("terms"), F.col("p.c").alias("counts"))

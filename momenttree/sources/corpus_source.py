"""format("topic_corpus"): rows of a synthetic corpus as a Python data source."""

from __future__ import annotations

import json
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from momenttree.runtime import ship


class Range(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


def tree_option(tree) -> str:
    """A tree as the value of the option "tree": shares of all nodes, words of the leaves."""
    leaves = set(tree.leaves())
    return json.dumps({p: [float(n.alpha), [float(x) for x in n.phi] if p in leaves else None] for p, n in tree.nodes.items()})


class CorpusReader(DataSourceReader):
    def __init__(self, options: dict):
        self.n = int(options.get("docs", "1000"))
        self.length = int(options.get("length", "40"))
        self.v = int(options.get("words", "50"))
        self.shape = tuple(int(x) for x in options.get("shape", "3").split("x"))
        self.seed = int(options.get("seed", "0"))
        self.parts = int(options.get("partitions", "4"))
        self.tree = options.get("tree")

    def partitions(self) -> list[Range]:
        edges = [self.n * k // self.parts for k in range(self.parts + 1)]
        return [Range(a, b) for a, b in zip(edges, edges[1:], strict=False)]

    def read(self, partition: Range) -> Iterator[tuple]:
        import numpy as np

        from momenttree.functions.paths import parent_of
        from momenttree.functions.tensor import seed_of
        from momenttree.operators.sampler import sample_tree

        if self.tree:
            nodes = json.loads(self.tree)
            alpha, phi = {p: a for p, (a, _) in nodes.items()}, {p: np.array(x) for p, (_, x) in nodes.items() if x}
        else:
            tree = sample_tree(self.shape, self.v, seed=self.seed)
            alpha, phi = {p: n.alpha for p, n in tree.nodes.items()}, {p: tree.nodes[p].phi for p in tree.leaves()}
        below: dict[str, list[str]] = {p: [] for p in alpha}
        for p in alpha:
            if parent_of(p) is not None:
                below[parent_of(p)].append(p)
        weights = {p: np.array([alpha[c] for c in own]) for p, own in below.items() if own}
        for doc in range(partition.first, partition.last):
            random = np.random.default_rng(seed_of(self.seed, doc))
            theta = {p: random.dirichlet(a) for p, a in weights.items()}
            left, words = {"o": np.arange(self.length)}, np.empty(self.length, np.int64)
            while left:
                p, at = left.popitem()
                if p in theta:
                    chosen = random.choice(len(theta[p]), len(at), p=theta[p])
                    left |= {below[p][z]: at[chosen == z] for z in np.unique(chosen)}
                else:
                    words[at] = random.choice(len(phi[p]), len(at), p=phi[p])
            yield doc, " ".join(f"w{x}" for x in words)


class TopicCorpus(DataSource):
    @classmethod
    def name(cls) -> str:
        return "topic_corpus"

    def schema(self) -> str:
        return "doc_id bigint, text string"

    def reader(self, schema) -> CorpusReader:
        return CorpusReader(self.options)


def register(spark: SparkSession) -> None:
    ship(spark)
    spark.dataSource.register(TopicCorpus)

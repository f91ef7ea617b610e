"""Collapsed Gibbs samplers whose state lives in a partitioned table.

State: (doc_id, words array<int>, z array<int>).  A sweep sends the global counts to all partitions, each resamples its
documents against its own copy, and the changes are added up: the usual approximate distributed form.  The supertopic
sampler takes a partition's documents in sequence; its seeds depend on (seed, sweep, document) only.  Plain LDA, whose chains
are long, keeps documents in blocks: the i-th words of a block's documents are drawn side by side, for all chains at once.
"""

from __future__ import annotations

import operator
import pickle
from bisect import bisect_left
from collections.abc import Callable, Iterable, Iterator, Sequence
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import RDD, StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from momenttree.functions import paths
from momenttree.functions.tensor import seed_of
from momenttree.operators.tree import Node, TopicTree
from momenttree.runtime import cut, shared_dir, ship

STATE = "doc_id bigint, words array<int>, z array<int>"

#: (words, labels, counts, totals, random) -> new labels; changes counts and totals in place.
Resample = Callable[[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.random.Generator], np.ndarray]


def tokens_of(bags: DataFrame) -> DataFrame:
    """doc_id, words with repeats, from bags."""
    return bags.select("doc_id", F.flatten(F.zip_with("terms", "counts", lambda t, c: F.array_repeat(t, c.cast("int")))).alias("words"))


def counts_of(state: DataFrame, v: int, n_labels: int, decode: Callable[[np.ndarray], np.ndarray] | None = None) -> np.ndarray:
    """(labels, words) counts; decode maps a label to the node that emits."""
    rows = state.select(F.explode(F.arrays_zip("words", "z")).alias("t")).groupBy("t.words", "t.z").agg(F.count("*").alias("n")).toPandas()
    out = np.zeros((n_labels, v))
    labels = rows["z"].to_numpy()
    np.add.at(out, (decode(labels) if decode else labels, rows["words"].to_numpy()), rows["n"].to_numpy())
    return out


def sweep(state: DataFrame, resample: Resample, counts: np.ndarray, seed: int) -> DataFrame:
    ship(state.sparkSession)
    sent = state.sparkSession.sparkContext.broadcast(counts)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = sent.value.copy()
        totals = own.sum(axis=1)
        for batch in batches:
            made = []
            for doc, words, z in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                made.append(resample(np.array(words, np.int64), np.array(z, np.int64), own, totals, np.random.default_rng(seed_of(seed, doc))).astype(np.int32))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(made, pa.list_(pa.int32()))], ["doc_id", "words", "z"])

    return state.select("doc_id", "words", "z").mapInArrow(run, STATE)


def start(tokens: DataFrame, n_labels: int, seed: int) -> DataFrame:
    label = lambda w, i: F.pmod(F.xxhash64(F.lit(seed), "doc_id", i), F.lit(n_labels)).cast("int")
    return cut(tokens.select("doc_id", "words", F.transform("words", label).alias("z")))


def chain(tokens: DataFrame, v: int, n_labels: int, n_nodes: int, resample: Resample, iters: int, seed: int, decode=None) -> tuple[DataFrame, np.ndarray]:
    state = start(tokens, n_labels, seed)
    counts = counts_of(state, v, n_nodes, decode)
    for k in range(iters):
        state = cut(sweep(state, resample, counts, seed_of(seed, k)))
        counts = counts_of(state, v, n_nodes, decode)
    return state, counts


#: Up to so many topics plain numbers are quicker than arrays of them.
FEW_TOPICS = 16


def lda_resample(k: int, alpha: float, eta: float) -> Resample:
    """Plain LDA: label = topic, one document after the other: the sequential chain, which `side_by_side` is tested against.

    Both forms do the same operations in the same order, so they draw the same labels.
    """

    def by_numbers(words, z, counts, totals, random):
        base = counts.shape[1] * eta
        names, place = np.unique(words, return_inverse=True)
        table, total, labels = counts[:, names].T.tolist(), totals.tolist(), z.tolist()
        own = np.bincount(z, minlength=k).astype(float).tolist()
        for i, (w, old, draw) in enumerate(zip(place.tolist(), z.tolist(), random.random(len(words)).tolist(), strict=True)):
            row = table[w]
            own[old] -= 1
            row[old] -= 1
            total[old] -= 1
            cumulated, last = [], 0.0
            for a, b, c in zip(own, row, total):  # noqa: B905
                last += (a + alpha) * (b + eta) / (c + base)
                cumulated.append(last)
            labels[i] = new = bisect_left(cumulated, draw * last)
            own[new] += 1
            row[new] += 1
            total[new] += 1
        counts[:, names], totals[:], z[:] = np.array(table).reshape(-1, k).T, total, labels
        return z

    def run(words, z, counts, totals, random):
        v = counts.shape[1]
        own = np.bincount(z, minlength=k).astype(float)
        draws = random.random(len(words))
        for i, w in enumerate(words):
            old = z[i]
            own[old] -= 1
            counts[old, w] -= 1
            totals[old] -= 1
            cumulated = np.cumsum((own + alpha) * (counts[:, w] + eta) / (totals + v * eta))
            new = int(np.searchsorted(cumulated, draws[i] * cumulated[-1]))
            z[i] = new
            own[new] += 1
            counts[new, w] += 1
            totals[new] += 1
        return z

    return by_numbers if k <= FEW_TOPICS else run


@dataclass
class Block:
    """Documents, the longest first; words: the first word of each, then the second of those that have two, and so on."""

    docs: np.ndarray
    sizes: np.ndarray
    words: np.ndarray
    z: np.ndarray  # chains x words

    def rows(self) -> np.ndarray:
        """How many documents have an i-th word."""
        return len(self.sizes) - np.searchsorted(self.sizes[::-1], np.arange(self.sizes.max(initial=0)), "right")

    def owners(self) -> np.ndarray:
        """The document, as a place in docs, of each word."""
        rows = self.rows()
        return np.arange(len(self.words)) - np.repeat(np.cumsum(rows) - rows, rows)

    def documents(self, chain: int) -> Iterator[tuple[int, list[int], list[int]]]:
        order = np.argsort(self.owners(), kind="stable")
        ends = np.cumsum(self.sizes)[:-1]
        for doc, words, z in zip(self.docs.tolist(), np.split(self.words[order], ends), np.split(self.z[chain][order], ends), strict=True):
            yield doc, words.tolist(), z.tolist()

    def random(self, seed: int, sweep: int) -> np.random.Generator:
        return np.random.default_rng(seed_of(seed, sweep, int(self.docs[0]), len(self.words)))


def block_of(docs: np.ndarray, sizes: np.ndarray, words: np.ndarray, k: int, seeds: Sequence[int]) -> Block:
    """words: of one document after the other.  Labels of sweep -1 are random."""
    order = np.argsort(-sizes, kind="stable")
    place = np.argsort(order)[np.repeat(np.arange(len(sizes)), sizes)]
    step = np.arange(len(words)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    made = Block(docs[order], sizes[order], words[np.lexsort((place, step))].astype(np.int32), np.empty((len(seeds), len(words)), np.min_scalar_type(k)))
    for c, seed in enumerate(seeds):
        made.z[c] = made.random(seed, -1).integers(0, k, len(words))
    return made


#: A block ends with the document that fills so many words.
BLOCK_WORDS = 1 << 18


def blocks(tokens: DataFrame, k: int, seeds: Sequence[int]) -> RDD:
    """Every document of tokens in a Block."""
    ship(tokens.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            words = batch.column(1)
            sizes, flat, docs = np.diff(words.offsets.to_numpy()).astype(np.int64), words.flatten().to_numpy(), batch.column(0).to_numpy()
            ends = np.cumsum(sizes)
            for part in np.split(np.arange(len(docs)), np.flatnonzero(np.diff((ends - 1) // BLOCK_WORDS)) + 1):
                if len(part):
                    made = block_of(docs[part], sizes[part], flat[ends[part[0]] - sizes[part[0]] : ends[part[-1]]], k, seeds)
                    yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(made)], pa.binary())], ["block"])

    return tokens.select("doc_id", "words").mapInArrow(run, "block binary").rdd.map(lambda r: pickle.loads(r.block))


def side_by_side(block: Block, counts: np.ndarray, totals: np.ndarray, alpha: float, eta: float, draws: np.ndarray) -> np.ndarray:
    """One sweep over a block, all chains: new labels; changes counts (topics x chains x words) and totals (topics x chains) in place.

    The i-th word of every document is drawn given all labels but its own, then the counts change.  With one document it is
    the sequential chain.
    """
    (k, chains, v), d, z = counts.shape, len(block.docs), block.z.astype(np.int64)
    chain = np.arange(chains)[:, None]
    own = np.bincount(((z * chains + chain) * d + block.owners()).ravel(), minlength=k * chains * d).astype(float).reshape(k, chains, d)
    flat_own, flat_counts, flat_totals = own.reshape(-1), counts.reshape(-1), totals.reshape(-1)
    end = 0
    for n in block.rows().tolist():
        at, end = end, end + n
        words, old = block.words[at:end], z[:, at:end].copy()
        mine = chain * d + np.arange(n)
        here = old * (chains * n) + np.arange(chains * n).reshape(chains, n)
        flat_own[old * (chains * d) + mine] -= 1
        weight = counts.take(words, axis=2)
        weight.reshape(-1)[here] -= 1
        weight += eta
        weight *= own[:, :, :n] + alpha
        base = totals + v * eta
        weight /= base[:, :, None]
        weight.reshape(-1)[here] *= (base / (base - 1)).reshape(-1)[old * chains + chain]
        np.cumsum(weight, axis=0, out=weight)
        new = (weight[:-1] < draws[:, at:end] * weight[-1]).sum(axis=0)
        flat_own[new * (chains * d) + mine] += 1
        z[:, at:end] = new
        moved = np.flatnonzero(new != old)
        if len(moved):
            left, found, who = old.reshape(-1)[moved], new.reshape(-1)[moved], moved // n
            where = who * v + words[moved - who * n]
            np.add.at(flat_counts, left * (chains * v) + where, -1.0)
            np.add.at(flat_counts, found * (chains * v) + where, 1.0)
            flat_totals += np.bincount(found * chains + who, minlength=k * chains) - np.bincount(left * chains + who, minlength=k * chains)
    return z


#: Sweeps after which the state is written to shared storage, and the state before it deleted there.
SWEEPS_A_CUT = 25
#: Where rows are one partition, so that tasks can share chains only, a task has so many chains.
CHAINS_A_TASK = 4


def _forget(state: RDD) -> None:
    """Deletes the stored rows of an earlier state."""
    jvm, path = state.ctx._jvm, state.getCheckpointFile()
    if path:
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(state.ctx._jsc.hadoopConfiguration()).delete(where, True)


def lda_chains(bags: DataFrame, v: int, k: int, seeds: Sequence[int], *, iters: int = 1000, alpha: float = 0.1, eta: float = 0.01) -> list[tuple[np.ndarray, np.ndarray, DataFrame]]:
    """phi (words x topics), topic shares and state of a chain for each seed.  A sweep is one job, whatever the number of chains.

    Blocks stay with the executors (in memory or on their disks) from sweep to sweep; only counts travel.  Rows of one
    partition have no other counts to wait for: a job makes all sweeps up to the next cut, with the same labels.
    """
    spark, chains = bags.sparkSession, len(seeds)
    context = spark.sparkContext
    shared_dir(spark)
    nothing = np.zeros((k, chains, v), np.int64)

    def counted(found: Iterable[Block]) -> Iterator[np.ndarray]:
        out = nothing.copy()
        for b in found:
            for c in range(chains):
                np.add.at(out, (b.z[c].astype(np.int64), c, b.words), 1)
        yield out

    def resampled(sent, sweeps: range) -> Callable[[Iterable], Iterator]:
        def run(found: Iterable) -> Iterator:
            counts = sent.value.astype(float)
            totals = counts.sum(axis=2)

            def swept(sweep: int, found: Iterable) -> Iterator[Block]:
                for b in found:
                    if isinstance(b, Block):
                        draws = np.stack([b.random(seed, sweep).random(len(b.words)) for seed in seeds])
                        yield Block(b.docs, b.sizes, b.words, side_by_side(b, counts, totals, alpha, eta, draws).astype(b.z.dtype))

            for sweep in sweeps[:-1]:
                found = list(swept(sweep, found))
            yield from swept(sweeps[-1], found)
            yield (counts - sent.value).astype(np.int64)  # the last row of a partition: how its counts changed

        return run

    state = blocks(tokens_of(bags), k, seeds)
    alone = state.getNumPartitions() == 1
    if alone and chains > CHAINS_A_TASK:
        with ThreadPoolExecutor() as pool:
            parts = pool.map(lambda at: lda_chains(bags, v, k, seeds[at : at + CHAINS_A_TASK], iters=iters, alpha=alpha, eta=eta), range(0, chains, CHAINS_A_TASK))
            return [flat for part in parts for flat in part]
    state = state.persist(StorageLevel.MEMORY_AND_DISK)
    state.checkpoint()
    counts = state.mapPartitions(counted).treeAggregate(nothing, operator.add, operator.add)
    stored, sent = state, []
    step = SWEEPS_A_CUT if alone else 1
    for sweep in range(0, iters, step):
        sent.append(context.broadcast(counts))
        sweeps = range(sweep, min(sweep + step, iters))
        after = state.mapPartitions(resampled(sent[-1], sweeps)).persist(StorageLevel.MEMORY_AND_DISK)
        last = sweeps[-1] == iters - 1 or sweeps[-1] % SWEEPS_A_CUT == SWEEPS_A_CUT - 1
        if last:
            after.checkpoint()
        counts = counts + after.filter(lambda b: not isinstance(b, Block)).treeAggregate(nothing, operator.add, operator.add)
        state.unpersist()
        state = after
        if last:
            _forget(stored)
            for old in sent[:-1]:  # the last one is still named by the state
                old.destroy()
            stored, sent = state, sent[-1:]
    state.unpersist()
    out = []
    for c in range(chains):
        smooth = counts[:, c] + eta
        rows = state.filter(lambda b: isinstance(b, Block)).flatMap(lambda b, c=c: b.documents(c))
        out.append(((smooth / smooth.sum(axis=1, keepdims=True)).T, counts[:, c].sum(axis=1) / max(counts[:, c].sum(), 1), spark.createDataFrame(rows, STATE, verifySchema=False)))
    return out


def lda_gibbs(bags: DataFrame, v: int, k: int, *, seed: int = 0, **options) -> tuple[np.ndarray, np.ndarray, DataFrame]:
    """phi (words x topics), topic shares, state."""
    return lda_chains(bags, v, k, (seed,), **options)[0]


def lda_variational(bags: DataFrame, v: int, k: int, *, iters: int = 20, seed: int = 0, optimizer: str = "online") -> tuple[np.ndarray, np.ndarray]:
    """phi and shares by Spark's own LDA."""
    from pyspark.ml.clustering import LDA
    from pyspark.ml.functions import array_to_vector

    dense = F.transform(F.sequence(F.lit(0), F.lit(v - 1)), lambda x: F.coalesce(F.element_at(F.map_from_arrays("terms", "counts"), x.cast("int")), F.lit(0.0)))
    frame = bags.select(array_to_vector(dense).alias("features"))
    model = LDA(k=k, maxIter=iters, seed=seed, optimizer=optimizer).fit(frame)
    topics = model.topicsMatrix().toArray()
    return topics / topics.sum(axis=0), topics.sum(axis=0) / topics.sum()


def chain_seed(seed: int, path: str) -> int:
    return seed_of(seed, path) % (1 << 31)


def recursive_lda(bags: DataFrame, v: int, *, widths: tuple[int, ...], iters: int = 1000, engine: str = "gibbs", split: str = "token", seed: int = 0, min_docs: int = 5, root: tuple[np.ndarray, np.ndarray, DataFrame] | None = None, **options) -> TopicTree:
    """LDA at a node, the corpus split by its result, and so on.

    token: every token goes to its label's child (variational: counts times the word's posterior); doc: whole documents go to their most frequent label.
    root: the Gibbs chain of the root, where it has run already.
    """
    tree = TopicTree({paths.ROOT: Node(paths.ROOT, np.full(v, 1 / v))})
    todo = [(paths.ROOT, bags)]
    while todo:
        path, own = todo.pop(0)
        level = paths.level_of(path)
        if level >= len(widths):
            continue
        n = own.count()
        if n < min_docs:
            tree.nodes[path].status = "starved"
            continue
        k, own_seed = widths[level], chain_seed(seed, path)
        if engine == "gibbs":
            phi, shares, state = root if root and path == paths.ROOT else lda_gibbs(own, v, k, iters=iters, seed=own_seed, **options)
            labelled = state.select("doc_id", F.explode(F.arrays_zip("words", "z")).alias("t")).select("doc_id", F.col("t.words").alias("term"), F.col("t.z").alias("z")).groupBy("doc_id", "term", "z").agg(F.count("*").cast("double").alias("c"))
        else:
            phi, shares = lda_variational(own, v, k, iters=iters, seed=own_seed)
            posterior = phi * shares
            posterior = posterior / posterior.sum(axis=1, keepdims=True)
            listed = own.sparkSession.createDataFrame([(x, z, float(posterior[x, z])) for x in range(v) for z in range(k)], "term int, z int, share double")
            labelled = own.select("doc_id", F.explode(F.arrays_zip("terms", "counts")).alias("t")).select("doc_id", F.col("t.terms").alias("term"), F.col("t.counts").alias("n")).join(F.broadcast(listed), "term").select("doc_id", "term", "z", (F.col("n") * F.col("share")).alias("c"))
        if split == "doc":
            best = labelled.groupBy("doc_id", "z").agg(F.sum("c").alias("n")).groupBy("doc_id").agg(F.max(F.struct("n", (-F.col("z")).alias("z"))).alias("b")).select("doc_id", (-F.col("b.z")).alias("z"))
            labelled = labelled.groupBy("doc_id", "term").agg(F.sum("c").alias("c")).join(best, "doc_id")
        if level + 1 < len(widths):
            labelled = cut(labelled)
        tree.nodes[path].status, tree.nodes[path].alpha0 = "inner", 1.0
        if path == paths.ROOT:
            tree.nodes[path].phi = phi @ shares
        for z in np.argsort(-shares, kind="stable"):
            child = f"{path}/{len(tree.children(path)) + 1}"
            tree.nodes[child] = Node(child, phi[:, z], float(shares[z]), None, float(tree.nodes[path].weight * shares[z]))
            if level + 1 < len(widths):
                pairs = F.array_sort(F.collect_list(F.struct("term", F.round("c").alias("c"))))
                part = labelled.where(F.col("z") == int(z)).where("round(c) > 0").groupBy("doc_id").agg(F.sum(F.round("c")).alias("len"), pairs.alias("p"))
                todo.append((child, cut(part.where("len >= 3").select("doc_id", "len", F.col("p.term").alias("terms"), F.col("p.c").alias("counts")))))
    tree.nodes = dict(sorted(tree.nodes.items()))
    return tree


def recursive_lda_runs(bags: DataFrame, v: int, *, widths: tuple[int, ...], seeds: Sequence[int], iters: int = 1000, split: str = "token", min_docs: int = 5, **options) -> list[TopicTree]:
    """The tree of `recursive_lda` for each seed; the chains of the root, which all see the same bags, run together."""
    flats = lda_chains(bags, v, widths[0], [chain_seed(s, paths.ROOT) for s in seeds], iters=iters, **options) if widths and bags.count() >= min_docs else [None] * len(seeds)
    return [recursive_lda(bags, v, widths=widths, iters=iters, split=split, seed=s, min_docs=min_docs, root=flat, **options) for s, flat in zip(seeds, flats, strict=True)]


@dataclass
class SupertopicModel:
    """1 root, n_super and n_sub topics; association[S, s] counts tokens that chose the pair."""

    phi_root: np.ndarray
    phi_super: np.ndarray
    phi_sub: np.ndarray
    association: np.ndarray
    tokens: int


def supertopic_gibbs(bags: DataFrame, v: int, *, n_super: int, n_sub: int, iters: int = 1000, alpha: float = 0.5, beta: float = 0.5, gamma: float = 1.0, eta: float = 0.01, seed: int = 0) -> SupertopicModel:
    """Each token has a supertopic, a subtopic and the level that emits it (root, super, sub).

    Label: ((S * n_sub) + s) * 3 + level; nodes are counted root, supertopics, subtopics.
    """
    n_labels, n_nodes = n_super * n_sub * 3, 1 + n_super + n_sub
    label = np.arange(n_labels)
    sup, sub, level = label // 3 // n_sub, label // 3 % n_sub, label % 3
    node = np.where(level == 0, 0, np.where(level == 1, 1 + sup, 1 + n_super + sub))

    def run(words, z, counts, totals, random):
        by_super = np.bincount(sup[z], minlength=n_super).astype(float)
        by_pair = np.bincount(sup[z] * n_sub + sub[z], minlength=n_super * n_sub).astype(float)
        by_level = np.bincount(level[z], minlength=3).astype(float)
        draws = random.random(len(words))
        for i, w in enumerate(words):
            old = z[i]
            by_super[sup[old]] -= 1
            by_pair[sup[old] * n_sub + sub[old]] -= 1
            by_level[level[old]] -= 1
            counts[node[old], w] -= 1
            totals[node[old]] -= 1
            emit = (counts[:, w] + eta) / (totals + v * eta)
            pair = (by_super[sup] + alpha) * (by_pair[sup * n_sub + sub] + beta) / (by_super[sup] + n_sub * beta)
            cumulated = np.cumsum(pair * (by_level[level] + gamma) * emit[node])
            new = int(np.searchsorted(cumulated, draws[i] * cumulated[-1]))
            z[i] = new
            by_super[sup[new]] += 1
            by_pair[sup[new] * n_sub + sub[new]] += 1
            by_level[level[new]] += 1
            counts[node[new], w] += 1
            totals[node[new]] += 1
        return z

    state, counts = chain(tokens_of(bags), v, n_labels, n_nodes, run, iters, seed, decode=lambda z: node[z])
    rows = state.select(F.explode("z").alias("z")).groupBy("z").agg(F.count("*").alias("n")).toPandas()
    association = np.zeros((n_super, n_sub))
    np.add.at(association, (sup[rows["z"]], sub[rows["z"]]), rows["n"].to_numpy())
    phi = ((counts + eta) / (counts + eta).sum(axis=1, keepdims=True)).T
    return SupertopicModel(phi[:, 0], phi[:, 1 : 1 + n_super], phi[:, 1 + n_super :], association, int(rows["n"].sum()))


def strongest_subtopics(model: SupertopicModel, n: int = 5) -> TopicTree:
    """Tree view: each supertopic with its n strongest subtopics."""
    tree = TopicTree({paths.ROOT: Node(paths.ROOT, model.phi_root, 1.0, 1.0, 1.0, "inner")})
    total = max(model.association.sum(), 1)
    for k, s in enumerate(np.argsort(-model.association.sum(axis=1), kind="stable"), 1):
        row = model.association[s]
        tree.nodes[f"o/{k}"] = Node(f"o/{k}", model.phi_super[:, s], float(row.sum() / total), 1.0, float(row.sum() / total), "inner")
        for j, u in enumerate(np.argsort(-row, kind="stable")[:n], 1):
            tree.nodes[f"o/{k}/{j}"] = Node(f"o/{k}/{j}", model.phi_sub[:, u], float(row[u] / max(row.sum(), 1)), None, float(row[u] / total))
    tree.nodes = dict(sorted(tree.nodes.items()))
    return tree


def nested_partition_gibbs(bags: DataFrame, v: int, *, height: int = 2, concentration: float = 1.0, eta: float = 0.1, zeta: float = 1.0, iters: int = 20, seed: int = 0) -> tuple[TopicTree, dict[int, str]]:
    """A nonparametric tree: every document follows one path of fixed height and may open new nodes; tokens choose levels.

    The chain is sequential by nature, so it runs in one task: for corpora that one task can hold (`LIMIT_DOCS`).
    Returns the tree and each document's leaf.
    """
    if bags.count() > LIMIT_DOCS:
        raise MemoryError(f"the nested partition sampler is sequential and takes at most {LIMIT_DOCS} documents")
    spark = bags.sparkSession
    ship(spark)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        docs = [(d, np.array(w)) for b in batches for d, w in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True)]
        docs.sort(key=lambda x: x[0])
        leaf, counts = _nested_chain(docs, v, height, concentration, eta, zeta, iters, seed)
        rows = [("doc", d, p, None) for d, p in leaf.items()] + [("node", None, p, c.tolist()) for p, c in sorted(counts.items())]
        yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows]), pa.array([r[1] for r in rows], pa.int64()), pa.array([r[2] for r in rows]), pa.array([r[3] for r in rows], pa.list_(pa.float64()))], ["kind", "doc_id", "path", "counts"])

    rows = tokens_of(bags).repartition(1).mapInArrow(run, "kind string, doc_id bigint, path string, counts array<double>").collect()
    nodes = {r.path: np.array(r.counts) for r in rows if r.kind == "node"}
    leaf = {r.doc_id: r.path for r in rows if r.kind == "doc"}
    names = {paths.ROOT: paths.ROOT}
    for k in range(1, height + 1):
        for old in sorted((p for p in nodes if paths.level_of(p) == k), key=lambda p: (p.rpartition("/")[0], -nodes[p].sum(), p)):
            parent = names[old.rpartition("/")[0]]
            names[old] = f"{parent}/{sum(names[q].startswith(parent + '/') and paths.level_of(q) == k for q in names if q != old) + 1}"
    total = max(sum(c.sum() for c in nodes.values()), 1)
    tree = TopicTree({names[p]: Node(names[p], (c + eta) / (c + eta).sum(), float(c.sum() / total), None, float(c.sum() / total), "leaf" if paths.level_of(p) == height else "inner") for p, c in nodes.items()})
    tree.nodes = dict(sorted(tree.nodes.items()))
    return tree, {d: names[p] for d, p in leaf.items()}


LIMIT_DOCS = 10_000


def _log_ratio(counts: np.ndarray, total: float, words: np.ndarray, how_many: np.ndarray, eta: float, v: int) -> float:
    """Log probability of words (with multiplicities) under a node's Dirichlet-multinomial, by rising factorials."""
    out = 0.0
    for w, c in zip(words, how_many, strict=True):
        out += np.log(counts[w] + eta + np.arange(c)).sum()
    return out - np.log(total + v * eta + np.arange(how_many.sum())).sum()


def _nested_chain(docs, v: int, height: int, concentration: float, eta: float, zeta: float, iters: int, seed: int):
    random = np.random.default_rng(seed)
    counts: dict[str, np.ndarray] = {}
    visits: dict[str, int] = {}
    fresh = 0
    levels = {d: random.integers(0, height + 1, len(w)) for d, w in docs}
    leaf: dict[int, str] = {}

    def change(d: int, words: np.ndarray, sign: int) -> None:
        parts = leaf[d].split("/")
        for k in range(height + 1):
            p = "/".join(parts[: k + 1])
            visits[p] = visits.get(p, 0) + sign
            np.add.at(counts.setdefault(p, np.zeros(v)), words[levels[d] == k], sign)
            if not visits[p]:
                del visits[p], counts[p]

    for _ in range(iters + 1):
        for d, words in docs:
            if d in leaf:
                change(d, words, -1)
            path = paths.ROOT
            for k in range(1, height + 1):
                own, many = np.unique(words[levels[d] == k], return_counts=True)
                options = sorted(p for p in visits if p.startswith(path + "/") and paths.level_of(p) == k)
                scores = [np.log(visits[p]) + _log_ratio(counts[p], counts[p].sum(), own, many, eta, v) for p in options]
                scores.append(np.log(concentration) + _log_ratio(np.zeros(v), 0.0, own, many, eta, v))
                weights = np.exp(np.array(scores) - max(scores))
                chosen = random.choice(len(scores), p=weights / weights.sum())
                if chosen == len(options):
                    fresh += 1
                    path = f"{path}/{fresh}"
                else:
                    path = options[chosen]
            leaf[d] = path
            change(d, words, 1)
            parts = path.split("/")
            chain_nodes = ["/".join(parts[: k + 1]) for k in range(height + 1)]
            totals = np.array([counts[p].sum() for p in chain_nodes])
            own = np.bincount(levels[d], minlength=height + 1).astype(float)
            for i, w in enumerate(words):
                old = levels[d][i]
                own[old] -= 1
                at = chain_nodes[old]
                counts[at][w] -= 1
                totals[old] -= 1
                now = np.array([counts[p][w] for p in chain_nodes])
                weight = (own + zeta) * (now + eta) / (totals + v * eta)
                new = int(random.choice(height + 1, p=weight / weight.sum()))
                levels[d][i] = new
                own[new] += 1
                counts[chain_nodes[new]][w] += 1
                totals[new] += 1
    return leaf, counts


def tune_concentration(bags: DataFrame, v: int, target: int, *, rounds: int = 5, **options) -> float:
    """The concentration, by bisection on a logarithmic scale, whose tree has about `target` topics."""
    low, high = 1e-3, 1e3
    for _ in range(rounds):
        mid = (low * high) ** 0.5
        n = len(nested_partition_gibbs(bags, v, concentration=mid, **options)[0].nodes)
        low, high = (mid, high) if n < target else (low, mid)
    return (low * high) ** 0.5

"""Recursive construction of topic trees by moments, level by level.

Siblings are independent, so all nodes of a level share their scans: one for M1 and E2 and one for the cores.  Small
vocabularies have E2 as a dense block on the driver; larger ones as stored edges, multiplied with thin blocks where they
lie; only if pairs would outweigh that does the implicit engine scan the bags once a sweep instead.  What depends on a node
only (its seed, its weights) is a function of its path, so revising one branch leaves every other bit as it was.

Inner nodes are treated as flat given their own words; where a child has children of its own, two tokens of the child
are not independent, so recovery is exact for one level and approximate above.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from momenttree.evaluation.cost import Ledger
from momenttree.functions import paths
from momenttree.functions import tensor as X
from momenttree.operators import moments
from momenttree.operators.tree import Node, TopicTree, collapse
from momenttree.plans import spectral
from momenttree.runtime import stored

VARIANTS = ("lean", "dense_m3", "dense_m2", "dense", "scan_power")
#: Second moments of larger vocabularies stay distributed, as edges.
EXPLICIT_WORDS = 4_096
#: Pairs of an average token's document for each column and sweep up to which edges are preferred to scans.
PAIRS_WORTH = 4


@dataclass(frozen=True)
class Settings:
    """How to build; widths maps a path to its number of children and overrides width."""

    width: int = 4
    height: int = 1
    widths: tuple[tuple[str, int], ...] = ()
    alpha0: float = 0.1
    starts: int = 30
    steps: int = 30
    variant: str = "lean"
    engine: str = "auto"  # explicit, sparse, implicit, sketch
    seed: int = 0
    min_len: float = moments.MIN_LEN
    self_pair: str = "plain"
    sweeps: int = 12

    def width_of(self, path: str) -> int:
        return dict(self.widths).get(path, self.width)


def choose_engine(v: int, sum_squares: float, nonzeros: float, k: int = 4, sweeps: int = 12) -> str:
    """explicit for small vocabularies; sparse where forming all pairs once costs less than the sweeps of the implicit engine.

    nonzeros and sum_squares: distinct words of the documents and their squares, summed.
    """
    if v <= EXPLICIT_WORDS:
        return "explicit"
    return "sparse" if sum_squares <= PAIRS_WORTH * nonzeros * (k + 8) * sweeps else "implicit"


def engine_for(bags: DataFrame, v: int, s: Settings) -> str:
    """The engine of a construction: that of the settings, or by counts of the bags where the vocabulary leaves a choice."""
    if s.engine != "auto" or v <= EXPLICIT_WORDS:
        return s.engine if s.engine != "auto" else "explicit"
    n = F.size("terms").cast("double")
    sums = bags.agg(F.sum(n).alias("n"), F.sum(n * n).alias("squares")).first()
    return choose_engine(v, sums.squares or 0.0, sums.n or 0.0, s.width, s.sweeps)


def child_weights(omega: np.ndarray | None, phi: np.ndarray, alpha: np.ndarray) -> list[np.ndarray]:
    """Each child's share of every word, times the parent's own share: the posterior telescopes along the path."""
    joint = phi * alpha
    total = joint.sum(axis=1, keepdims=True)
    share = np.divide(joint, total, out=np.zeros_like(joint), where=total > 0)
    own = np.ones(len(phi)) if omega is None else omega
    return [own * share[:, z] for z in range(phi.shape[1])]


def word_weights(tree: TopicTree) -> moments.Weights:
    """path -> weight of every word, 1 at the root."""
    out: moments.Weights = {paths.ROOT: None}
    for k in range(tree.height()):
        for path in tree.level(k):
            own = tree.children(path)
            if own:
                phi, alpha = np.stack([tree.nodes[c].phi for c in own], axis=1), np.array([tree.nodes[c].alpha for c in own])
                out |= dict(zip(own, child_weights(out[path], phi, alpha), strict=True))
    return out


def _whitener(u: np.ndarray, sigma: np.ndarray, m1: np.ndarray, alpha0: float, k: int) -> tuple[X.Whitener, int]:
    """The widest whitener of at most k columns that the spectrum supports."""
    while k:
        try:
            return X.lean_whitener(u[:, :k], sigma[:k], m1, alpha0), k
        except X.RankTooLow as low:
            k = min(low.found, k - 1)
    raise X.RankTooLow(0, 1)


def _flat_lean(bags: DataFrame, v: int, todo: dict[str, int], weights: moments.Weights, s: Settings, ledger: Ledger, eigs: dict, m1: dict[str, np.ndarray]) -> dict[str, X.Flat]:
    whiteners = {}
    for p, k in todo.items():
        try:
            whiteners[p] = _whitener(eigs[p][1], eigs[p][0], m1[p], s.alpha0, k)[0]
        except X.RankTooLow:
            continue
    if not whiteners:
        return {}
    parts = moments.project_third(bags, v, {p: w.w for p, w in whiteners.items()}, {p: weights[p] for p in whiteners}, ledger=ledger, min_len=s.min_len, self_pair=s.self_pair)
    out = {}
    for p, w in whiteners.items():
        core = X.core_from(parts[p].p1, parts[p].p2, parts[p].g, w.w, m1[p], s.alpha0, parts[p].n_docs)
        out[p] = X.recover(X.power_decompose(core, starts=s.starts, steps=s.steps, seed=X.seed_of(s.seed, p)), w, s.alpha0)
    return out


def _level(bags: DataFrame, v: int, todo: dict[str, int], weights: moments.Weights, s: Settings, ledger: Ledger) -> tuple[dict[str, X.Flat], dict[str, float]]:
    """Flat decompositions of the nodes of one level, and how many documents each has."""
    own = {p: weights[p] for p in todo}
    options = {"min_len": s.min_len, "self_pair": s.self_pair}
    if s.variant == "dense_m3":
        moments.guard(v, 3, moments.DENSE_THIRD_WORDS)
    engine = "explicit" if s.variant in ("dense_m2", "dense_m3") else engine_for(bags, v, s)
    seeds = {p: X.seed_of(s.seed, p, "block") for p in todo}
    if engine == "explicit":
        found = moments.moments_of(bags, v, own, ledger=ledger, **options)
        docs, m1 = {p: m.n_docs for p, m in found.items()}, {p: m.m1 for p, m in found.items()}
        ledger.nonzeros = max([ledger.nonzeros, *(int((np.abs(m.e2) > 1e-15).sum()) for m in found.values())])
        todo = {p: k for p, k in todo.items() if p in found}
        eigs = {p: X.largest_eigs(found[p].e2, k) for p, k in todo.items()}
    else:
        pairs = engine == "sparse"
        sums = moments.level_moments(bags, v, own, pairs=pairs, ledger=ledger, **options)
        if pairs:
            sums = stored(sums, "level_moments")
        docs, m1 = {}, {}
        for p, rows in sums.where("x2 = -1").toPandas().groupby("path"):
            x, total = rows["x1"].to_numpy(), rows["total"].to_numpy()
            docs[p], m1[p] = float(total[x == -1][0]), np.zeros(v)
            m1[p][x[x >= 0]] = total[x >= 0] / docs[p]
        todo = {p: k for p, k in todo.items() if p in docs}
        found = {}
        if pairs:
            edges = sums.where("x2 >= 0 and abs(total) > 1e-15")
            ledger.nonzeros = max([ledger.nonzeros, *(r.n for r in edges.groupBy("path").agg(F.sum(F.when(F.col("x1") < F.col("x2"), 2).otherwise(1)).alias("n")).collect())])
            product = spectral.edge_product(edges.select("path", "x1", "x2", F.col("total").alias("v")), v, docs)
        else:
            product = spectral.scan_product(bags, v, own, ledger, **options)
        eigs = spectral.sketch_eigs(product, v, todo, seeds) if engine == "sketch" else spectral.top_eigs(product, v, todo, seeds, sweeps=s.sweeps)
    if s.variant == "lean":
        return _flat_lean(bags, v, todo, weights, s, ledger, eigs, m1), docs
    if s.variant == "scan_power":
        return {p: _scan_power(bags, v, p, k, weights[p], s, ledger, eigs[p], m1[p]) for p, k in todo.items()}, docs
    out = {}
    for p, k in todo.items():
        if s.variant == "dense_m2":
            m2 = (s.alpha0 + 1) * found[p].e2 - s.alpha0 * np.outer(m1[p], m1[p])
            w = X.whiten(*reversed(X.largest_eigs(m2, k)))
            parts = moments.project_third(bags, v, {p: w.w}, {p: weights[p]}, ledger=ledger, **options)[p]
            core = X.core_from(parts.p1, parts.p2, parts.g, w.w, m1[p], s.alpha0, parts.n_docs, found[p].e2)
        else:  # dense_m3: M2 is avoided, M3 is built
            w = X.lean_whitener(eigs[p][1], eigs[p][0], m1[p], s.alpha0)
            ledger.scans += 1
            e3 = moments.third_moment_dense(scaled_bags(bags, weights[p]), v, min_len=s.min_len)
            _, m3 = X.centred_moments(m1[p], found[p].e2, e3, s.alpha0)
            core = X.multilinear(m3, w.w, w.w, w.w)
        out[p] = X.recover(X.power_decompose(core, starts=s.starts, steps=s.steps, seed=X.seed_of(s.seed, p)), w, s.alpha0)
    return out, docs


def scaled_bags(bags: DataFrame, omega: np.ndarray | None) -> DataFrame:
    """bags with counts times a node's word weights; for the dense variants, whose vocabularies are small."""
    if omega is None:
        return bags
    listed = F.array(*(F.lit(float(x)) for x in omega))
    counts = F.zip_with("terms", "counts", lambda t, c: c * F.get(listed, t))
    return bags.select("doc_id", "len", "terms", counts.alias("counts"))


def _scan_power(bags: DataFrame, v: int, path: str, k: int, omega: np.ndarray | None, s: Settings, ledger: Ledger, eig: tuple, m1: np.ndarray) -> X.Flat:
    """Power iteration that never stores the core: every update of all starts is one scan contracted with them."""
    w, k = _whitener(eig[1], eig[0], m1, s.alpha0, k)
    random = np.random.default_rng(X.seed_of(s.seed, path))
    b = w.w.T @ m1
    values, vectors = [], []

    def contracted(q: np.ndarray) -> np.ndarray:
        """Core applied to (q, q) for each column of q, from one scan."""
        ledger.scans += 1
        p1, p2, g, n = contract_scan(bags, v, w.w, q, omega, s.min_len)
        wq = w.w @ q
        third = (p1 - p2 + 2 * w.w.T @ (g[:, None] * wq**2)) / n
        bq = b @ q
        e2 = (np.eye(k) + s.alpha0 * np.outer(b, b)) / (s.alpha0 + 1)
        u = 2 * (e2 @ q) * bq + b[:, None] * np.einsum("is,ij,js->s", q, e2, q)
        out = 0.5 * (s.alpha0 + 1) * (s.alpha0 + 2) * third - 0.5 * s.alpha0 * (s.alpha0 + 1) * u + s.alpha0**2 * b[:, None] * bq**2
        for value, vector in zip(values, vectors, strict=True):
            out = out - value * vector[:, None] * (vector @ q) ** 2
        return out

    for _ in range(k):
        q = random.normal(size=(k, s.starts))
        q /= np.linalg.norm(q, axis=0)
        for _ in range(s.steps):
            q = contracted(q)
            q /= np.linalg.norm(q, axis=0)
        gains = (contracted(q) * q).sum(axis=0)
        best = int(np.argmax(gains))
        values.append(float(gains[best]))
        vectors.append(q[:, best])
    return X.recover(X.Pairs(np.array(values), np.array(vectors).T, 0.0), w, s.alpha0)


def contract_scan(bags: DataFrame, v: int, w: np.ndarray, q: np.ndarray, omega: np.ndarray | None, min_len: float) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
    """Sums over documents of the first two terms of the third moment contracted with each column of q, and per-word sums."""
    import pyarrow as pa

    sent = bags.sparkSession.sparkContext.broadcast((w, q, omega))
    k, n_starts = q.shape

    def kernel(batches):
        w, q, omega = sent.value
        p1, p2, g, n = np.zeros((k, n_starts)), np.zeros((k, n_starts)), np.zeros(v), 0
        for _, owner, terms, counts in moments.flat_chunks(batches):
            c = moments.node_chunk(owner, terms, counts, omega, min_len)
            if not c.n:
                continue
            n += c.n
            scale = 1 / (c.length * (c.length - 1) * (c.length - 2))
            rows = w[c.terms]
            y = c.by_doc(c.counts[:, None] * rows)
            rq, yq = rows @ q, y @ q
            p1 += (scale[:, None] * y).T @ yq**2
            squares = c.by_doc(c.counts[:, None] * rq**2)
            crossed = np.stack([c.by_doc(c.counts[:, None] * rows * rq[:, [j]]) for j in range(n_starts)], axis=2)
            p2 += (scale[:, None] * y).T @ squares + 2 * np.einsum("d,dks,ds->ks", scale, crossed, yq)
            g += c.by_term(c.counts * scale[c.owner], v)
        if n:
            flat = np.concatenate([[float(n)], p1.ravel(), p2.ravel(), g])
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(flat))), pa.array(flat)], ["at", "total"])

    summed = moments._scan(bags, kernel, "at bigint, total double").groupBy("at").agg(F.sum("total").alias("total")).toPandas().sort_values("at")["total"].to_numpy()
    size = k * n_starts
    return summed[1 : 1 + size].reshape(k, n_starts), summed[1 + size : 1 + 2 * size].reshape(k, n_starts), summed[1 + 2 * size :], float(summed[0])


def decompose(bags: DataFrame, v: int, k: int, ledger: Ledger | None = None, **settings) -> X.Flat:
    """One level: LDA by moments."""
    s = Settings(width=k, height=1, **settings)
    if s.variant == "dense":
        return _dense_root(bags, v, s, ledger or Ledger())[0]
    found, _ = _level(bags, v, {paths.ROOT: k}, {paths.ROOT: None}, s, ledger or Ledger())
    if paths.ROOT not in found:
        raise X.RankTooLow(0, k)
    return found[paths.ROOT]


def _grow(tree: TopicTree, path: str, flat: X.Flat, s: Settings, docs: float) -> list[str]:
    parent = tree.nodes[path]
    parent.alpha0, parent.status = float(s.alpha0), "inner"
    made = []
    total = flat.shares.sum()
    for z in range(flat.phi.shape[1]):
        child = f"{path}/{z + 1}"
        tree.nodes[child] = Node(child, flat.phi[:, z], float(flat.alpha[z]), None, float(parent.weight * flat.shares[z] / total), "leaf", float(flat.clipped[z]))
        made.append(child)
    return made


def build_tree(bags: DataFrame, v: int, ledger: Ledger | None = None, *, start: TopicTree | None = None, within: str = paths.ROOT, **settings) -> TopicTree:
    """The tree of the given widths and height; with start and within, only the subtree of one node is made anew.

    A node whose documents are all too short becomes a leaf with status "starved"; one whose spectrum supports no topic
    "flat".  Widths are reduced to what the spectrum supports.
    """
    s = Settings(**settings)
    if s.variant not in VARIANTS:
        raise ValueError(f"variant {s.variant!r} is none of {VARIANTS}")
    ledger = ledger or Ledger()
    if s.variant == "dense":
        if start is not None:
            raise ValueError("the dense variant conditions moments from the root down; it is built whole")
        return _build_dense(bags, v, s, ledger)
    tree = collapse(start, [within]) if start is not None else TopicTree({paths.ROOT: Node(paths.ROOT, np.zeros(v))})
    weights = word_weights(tree) if start is not None else {paths.ROOT: None}
    frontier = [within]
    bottom = s.height
    while frontier:
        todo = {p: min(s.width_of(p), v) for p in frontier if paths.level_of(p) < bottom and s.width_of(p) > 0}
        frontier = []
        if not todo:
            break
        found, docs = _level(bags, v, todo, weights, s, ledger)
        for p in todo:
            if p in found:
                made = _grow(tree, p, found[p], s, docs[p])
                if p == paths.ROOT:
                    tree.nodes[p].phi = found[p].phi @ (found[p].shares / found[p].shares.sum())
                weights |= dict(zip(made, child_weights(weights[p], found[p].phi, found[p].alpha), strict=True))
                frontier += made
            else:
                tree.nodes[p].status = "flat" if p in docs else "starved"
    tree.nodes = dict(sorted(tree.nodes.items()))
    tree.scans = ledger.scans
    return tree


def revise(tree: TopicTree, bags: DataFrame, path: str, *, n_children: int | None = None, height: int | None = None, ledger: Ledger | None = None, **settings) -> TopicTree:
    """One node's subtree with another number of children or another depth; no other node changes in any bit."""
    widths = dict(settings.pop("widths", ()))
    if n_children is not None:
        widths[path] = n_children
    return build_tree(bags, tree.v, ledger, start=tree, within=path, widths=tuple(sorted(widths.items())), height=tree.height() if height is None else height, **settings)


def expand(tree: TopicTree, bags: DataFrame, path: str, k: int, **settings) -> TopicTree:
    """k children under one leaf."""
    return revise(tree, bags, path, n_children=k, height=paths.level_of(path) + 1, **settings)


def prune(tree: TopicTree, path: str) -> TopicTree:
    return collapse(tree, [path])


# The dense reference: moments of the root only, conditioned downwards.


def _dense_moments(bags: DataFrame, v: int, s: Settings, ledger: Ledger) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    moments.guard(v, 3, moments.DENSE_THIRD_WORDS)
    root = moments.moments_of(bags, v, min_len=s.min_len, ledger=ledger)[paths.ROOT]
    ledger.scans += 1
    return root.m1, root.e2, moments.third_moment_dense(bags, v, min_len=s.min_len)


def _flat_dense(m1: np.ndarray, e2: np.ndarray, e3: np.ndarray, k: int, s: Settings, path: str) -> X.Flat:
    m2, m3 = X.centred_moments(m1, e2, e3, s.alpha0)
    values, vectors = X.largest_eigs(m2, k)
    k = max(1, int((values > 1e-12 * max(values[0], 1e-300)).sum()))
    w = X.whiten(vectors[:, :k], values[:k])
    return X.recover(X.power_decompose(X.multilinear(m3, w.w, w.w, w.w), starts=s.starts, steps=s.steps, seed=X.seed_of(s.seed, path)), w, s.alpha0)


def _dense_root(bags: DataFrame, v: int, s: Settings, ledger: Ledger) -> tuple[X.Flat, tuple]:
    parts = _dense_moments(bags, v, s, ledger)
    return _flat_dense(*parts, s.width_of(paths.ROOT), s, paths.ROOT), parts


def condition_moments(m1: np.ndarray, e2: np.ndarray, e3: np.ndarray | None, alpha: np.ndarray, phi: np.ndarray, child: int) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
    """A child's moments from its parent's: each entry times the probability that all its tokens came from the child."""

    def scaled(m: np.ndarray, order: int) -> np.ndarray:
        all_ways = X.population_moments(alpha, phi, order)
        own = np.zeros_like(alpha)
        own[child] = 1
        one = phi[:, child]
        a = alpha[child]
        weight = np.prod([a + j for j in range(order)]) / np.prod([alpha.sum() + j for j in range(order)])
        mine = weight * X.outer(*[one] * order) if order > 1 else weight * one
        out = np.divide(m * mine, all_ways, out=np.zeros_like(m), where=all_ways > 0)
        return out / out.sum() if out.sum() > 0 else out

    return scaled(m1, 1), scaled(e2, 2), scaled(e3, 3) if e3 is not None else None


def _build_dense(bags: DataFrame, v: int, s: Settings, ledger: Ledger) -> TopicTree:
    tree = TopicTree({paths.ROOT: Node(paths.ROOT, np.zeros(v))})
    todo = [(paths.ROOT, _dense_moments(bags, v, s, ledger))]
    while todo:
        path, parts = todo.pop(0)
        k = min(s.width_of(path), v)
        if paths.level_of(path) >= s.height or not k:
            continue
        flat = _flat_dense(*parts, k, s, path)
        made = _grow(tree, path, flat, s, 0.0)
        if path == paths.ROOT:
            tree.nodes[path].phi = flat.phi @ (flat.shares / flat.shares.sum())
        todo += [(child, condition_moments(*parts, flat.alpha, flat.phi, z)) for z, child in enumerate(made)]
    tree.nodes = dict(sorted(tree.nodes.items()))
    tree.scans = ledger.scans
    return tree

"""EM clustering of the word co-occurrence network, recursively on softly split edges."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from momenttree.functions import paths
from momenttree.functions.tensor import seed_of
from momenttree.operators.tree import Node, TopicTree
from momenttree.runtime import cut, ship

EDGES = "x1 int, x2 int, w double"


@dataclass
class NetworkFit:
    """Edge (x, y) has a Poisson weight of mean sum_z rho_z theta_zx theta_zy."""

    rho: np.ndarray
    theta: np.ndarray  # words x clusters
    likelihood: list[float]


def _shares(rho: np.ndarray, theta: np.ndarray, x1: np.ndarray, x2: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    joint = rho * theta[x1] * theta[x2]
    total = joint.sum(axis=1)
    return np.divide(joint, total[:, None], out=np.full_like(joint, 1 / len(rho)), where=total[:, None] > 0), total


def _step(edges: DataFrame, v: int, rho: np.ndarray, theta: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
    """One E and M step in one pass over the edges: tasks add their shares up, sums come back."""
    k = len(rho)
    sent = edges.sparkSession.sparkContext.broadcast((rho, theta))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rho, theta = sent.value
        sums, gained = np.zeros((v, k)), 0.0
        for b in batches:
            x1, x2, w = (b.column(i).to_numpy() for i in range(3))
            share, total = _shares(rho, theta, x1, x2)
            part = share * w[:, None]
            for z in range(k):
                sums[:, z] += np.bincount(x1, part[:, z], v) + np.bincount(x2, part[:, z], v)
            gained += float((w * np.log(np.maximum(total, 1e-300))).sum())
        flat = np.append(sums.ravel(), gained)
        at = np.flatnonzero(flat)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(flat[at])], ["at", "total"])

    rows = edges.select("x1", "x2", "w").mapInArrow(run, "at bigint, total double").groupBy("at").agg(F.sum("total").alias("total")).toPandas()
    flat = np.zeros(v * k + 1)
    flat[rows["at"].to_numpy()] = rows["total"].to_numpy()
    sums = flat[:-1].reshape(v, k)
    mass = sums.sum(axis=0)
    return mass / 2, np.divide(sums, mass, out=np.full_like(sums, 1 / v), where=mass > 0), float(flat[-1] - rho.sum())


def cluster(edges: DataFrame, v: int, k: int, *, iters: int = 50, tol: float = 1e-6, restarts: int = 1, seed: int = 0) -> NetworkFit:
    """The best of `restarts` runs by likelihood, which never falls within a run."""
    ship(edges.sparkSession)
    total = edges.agg(F.sum("w")).first()[0] or 0.0
    best = None
    for r in range(restarts):
        random = np.random.default_rng(seed_of(seed, r))
        rho, theta, path = np.full(k, total / k), random.dirichlet(np.ones(v), k).T, []
        for _ in range(iters):
            new_rho, new_theta, likelihood = _step(edges, v, rho, theta)
            path.append(likelihood)
            rho, theta = new_rho, new_theta
            if len(path) > 1 and abs(path[-1] - path[-2]) <= tol * max(abs(path[-1]), 1):
                break
        fit = NetworkFit(rho, theta, path)
        if best is None or fit.likelihood[-1] > best.likelihood[-1]:
            best = fit
    return best


def split_edges(edges: DataFrame, fit: NetworkFit, min_edge: float = 0.0) -> DataFrame:
    """z, x1, x2, w: every edge shared out among the clusters; shares sum to the edge, those below min_edge are dropped."""
    sent = edges.sparkSession.sparkContext.broadcast((fit.rho, fit.theta))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rho, theta = sent.value
        for b in batches:
            x1, x2, w = (b.column(i).to_numpy() for i in range(3))
            share, _ = _shares(rho, theta, x1, x2)
            n, k = share.shape
            yield pa.RecordBatch.from_arrays([pa.array(np.tile(np.arange(k, dtype=np.int32), n)), pa.array(np.repeat(x1, k)), pa.array(np.repeat(x2, k)), pa.array((share * w[:, None]).ravel())], ["z", "x1", "x2", "w"])

    out = edges.select("x1", "x2", "w").mapInArrow(run, "z int, x1 int, x2 int, w double")
    return out.where(F.col("w") >= min_edge) if min_edge > 0 else out


def pair_network_em(edges: DataFrame, v: int, *, widths: tuple[int, ...], iters: int = 50, restarts: int = 1, min_edge: float = 0.0, seed: int = 0) -> TopicTree:
    """A tree of the given widths; edges: x1, x2, w of the corpus."""
    tree = TopicTree({paths.ROOT: Node(paths.ROOT, np.full(v, 1 / v))})
    todo = [(paths.ROOT, edges)]
    while todo:
        path, own = todo.pop(0)
        level = paths.level_of(path)
        if level >= len(widths):
            continue
        fit = cluster(own, v, widths[level], iters=iters, restarts=restarts, seed=seed_of(seed, path))
        share = fit.rho / max(fit.rho.sum(), 1e-300)
        order = np.argsort(-share, kind="stable")
        tree.nodes[path].status, tree.nodes[path].alpha0 = "inner", 1.0
        if path == paths.ROOT:
            tree.nodes[path].phi = fit.theta @ share
        parts = cut(split_edges(own, fit, min_edge)) if level + 1 < len(widths) else None
        for j, z in enumerate(order, 1):
            child = f"{path}/{j}"
            tree.nodes[child] = Node(child, fit.theta[:, z], float(share[z]), None, float(tree.nodes[path].weight * share[z]))
            if parts is not None:
                todo.append((child, parts.where(F.col("z") == int(z)).select("x1", "x2", "w")))
    tree.nodes = dict(sorted(tree.nodes.items()))
    return tree

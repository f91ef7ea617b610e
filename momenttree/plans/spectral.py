"""Largest eigenpairs of a second moment that may only be given as a product with thin matrices."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from momenttree.functions.tensor import largest_eigs
from momenttree.operators import moments
from momenttree.runtime import group_nodes, ship, stored

Product = Callable[[dict[str, np.ndarray]], dict[str, np.ndarray]]


def start_block(v: int, width: int, seed: int) -> np.ndarray:
    return np.linalg.qr(np.random.default_rng(seed).normal(size=(v, width)))[0]


def top_eigs(product: Product, v: int, widths: dict[str, int], seeds: dict[str, int], *, oversample: int = 8, sweeps: int = 12, tol: float = 1e-9) -> dict[str, tuple[np.ndarray, np.ndarray]]:
    """path -> (values, vectors) of the largest algebraic eigenvalues, for all nodes of a level at once.

    Block subspace iteration with a Rayleigh-Ritz step; each sweep is one product, so one scan serves the whole level.
    Nodes that have settled leave the product.
    """
    size = {p: min(k + oversample, v) for p, k in widths.items()}
    q = {p: start_block(v, size[p], seeds[p]) for p in widths}
    out: dict[str, tuple[np.ndarray, np.ndarray]] = {}
    last: dict[str, np.ndarray] = {}
    for sweep in range(sweeps):
        y = product(q)
        for p in list(q):
            values, turn = np.linalg.eigh((q[p].T @ y[p] + y[p].T @ q[p]) / 2)
            order = np.argsort(values)[::-1][: widths[p]]
            out[p] = values[order], q[p] @ turn[:, order]
            if sweep and np.abs(values[order] - last[p]).max() <= tol * max(abs(values[order][0]), 1e-300):
                del q[p]
            else:
                last[p], q[p] = values[order], np.linalg.qr(y[p])[0]
        if not q:
            break
    return out


def sketch_eigs(product: Product, v: int, widths: dict[str, int], seeds: dict[str, int], *, oversample: int = 64) -> dict[str, tuple[np.ndarray, np.ndarray]]:
    """Single-scan form: with Y = E2 Q for a random block Q, E2 is taken as Y (Q'Y)^+ Y'.

    Q'Y is cut to its largest positive eigenvalues first: the tail of an empirical E2 is not positive, and its inverse
    would drown the rest.  Coarser than top_eigs, which the oversampling makes up for only in part.
    """
    q = {p: start_block(v, min(k + oversample, v), seeds[p]) for p, k in widths.items()}
    out = {}
    for p, y in product(q).items():
        values, turn = largest_eigs(q[p].T @ y, min(widths[p] + 8, y.shape[1]))
        good = values > 1e-3 * values[0]
        thin = y @ (turn[:, good] / np.sqrt(values[good]))
        basis, scale, _ = np.linalg.svd(thin, full_matrices=False)
        out[p] = scale[: widths[p]] ** 2, basis[:, : widths[p]]
    return out


def _groups(q: dict[str, np.ndarray], v: int, weighted: int = 0) -> list[list[str]]:
    """Nodes whose blocks (and weights) are sent together, by BLOCK_BYTES."""
    width = max(m.shape[1] for m in q.values())
    return group_nodes(list(q), 8 * v * (width + weighted), moments.BLOCK_BYTES)


def scan_product(bags: DataFrame, v: int, weights: moments.Weights, ledger, **options) -> Product:
    """E2 Q by a scan over the bags; thinner blocks are padded so that one scan carries all nodes that fit."""

    def run(q: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
        width = max(m.shape[1] for m in q.values())
        out = {}
        for names in _groups(q, v, 1):
            padded = {p: np.pad(q[p], ((0, 0), (0, width - q[p].shape[1]))) for p in names}
            ledger.scans += 1
            found = moments.applied(moments.second_moment_apply(bags, v, padded, {p: weights[p] for p in names}, **options), v, width)
            out |= {p: found[p][1][:, : q[p].shape[1]] for p in names}
        return out

    return run


#: Rows of E2 that are dealt and handed on together.
ROWS_TOGETHER = 1_024


def edge_product(edges: DataFrame, v: int, docs: dict[str, float] | None = None) -> Product:
    """E2 Q from edges (path, x1 <= x2, v), divided by the number of documents where v are sums.

    Both directions of the edges are dealt once by node and range of rows and stored, so each row of the result is
    summed in one task, in numpy; blocks are broadcast for as many nodes as BLOCK_BYTES allows.  The bags are not scanned.
    """
    both = edges.select("path", F.col("x1").alias("x"), F.col("x2").alias("y"), "v").union(edges.where("x1 <> x2").select("path", F.col("x2").alias("x"), F.col("x1").alias("y"), "v"))
    dealt = stored(both.repartition("path", F.floor(F.col("x") / ROWS_TOGETHER)).sortWithinPartitions("path", "x"), "edges")
    spark = edges.sparkSession
    ship(spark)

    def run(q: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
        out = {p: np.zeros_like(m) for p, m in q.items()}
        for names in _groups(q, v):
            sent = spark.sparkContext.broadcast({p: q[p] for p in names})

            def kernel(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
                blocks = sent.value
                sums: dict[str, np.ndarray] = {}
                for batch in batches:
                    found = pc.dictionary_encode(batch.column(0))
                    codes, names_here = found.indices.to_numpy(), found.dictionary.to_pylist()
                    x, y, value = (batch.column(k).to_numpy() for k in (1, 2, 3))
                    fresh = np.append(True, (np.diff(codes) != 0) | (np.diff(x) != 0))[: len(x)]
                    for code, name in enumerate(names_here):
                        at = np.flatnonzero(codes == code)
                        block = blocks[name]
                        starts = np.flatnonzero(fresh[at])  # rows are sorted: each run of equal x is summed at once
                        total = sums.setdefault(name, np.zeros((v, block.shape[1])))
                        np.add.at(total, x[at[starts]], np.add.reduceat(value[at, None] * block[y[at]], starts, axis=0))
                for name, total in sums.items():
                    for r in np.unique(np.flatnonzero(total.any(axis=1)) // ROWS_TOGETHER):
                        yield pa.RecordBatch.from_arrays([pa.array([name]), pa.array([r]), pa.array([total[r * ROWS_TOGETHER : (r + 1) * ROWS_TOGETHER].tobytes()])], ["path", "part", "payload"])

            chosen = dealt.where(F.col("path").isin(names))
            for r in chosen.mapInArrow(kernel, "path string, part bigint, payload binary").toLocalIterator():
                rows = np.frombuffer(r.payload).reshape(-1, q[r.path].shape[1])
                out[r.path][r.part * ROWS_TOGETHER : r.part * ROWS_TOGETHER + len(rows)] += rows
        return {p: m / docs[p] for p, m in out.items()} if docs else out

    return run

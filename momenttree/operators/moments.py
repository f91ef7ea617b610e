"""Empirical moments of bags, for one node or for a whole level of nodes in one scan.

A node's bags are the corpus' bags with every count scaled by the node's weight of the word (1 at the root), so a level
needs no rewritten corpus: the weights are broadcast.  A document counts for a node if its scaled length reaches
min_len.  Each task sums into arrays of bounded size and hands on sums, which one shuffle adds up.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from momenttree.runtime import group_nodes, ship

MIN_LEN = 3.0
#: A task's dense pair block may take so many bytes; a larger vocabulary is summed sparsely.
BLOCK_BYTES = 256 << 20
#: Pairs that the sparse form holds before it hands its sums on.
PAIRS_HELD = 4_000_000
DOCS_AT_ONCE = 512


@dataclass
class Chunk:
    """Documents of one node as flat arrays; owner numbers the documents from 0."""

    owner: np.ndarray
    terms: np.ndarray
    counts: np.ndarray
    omega: np.ndarray  # weight of each entry's word
    length: np.ndarray

    @property
    def n(self) -> int:
        return len(self.length)

    def by_doc(self, values: np.ndarray) -> np.ndarray:
        """Sums over each document's entries."""
        if values.ndim == 1:
            return np.bincount(self.owner, values, self.n)
        return np.stack([np.bincount(self.owner, values[:, j], self.n) for j in range(values.shape[1])], axis=1) if values.shape[1] else np.zeros((self.n, 0))

    def by_term(self, values: np.ndarray, v: int) -> np.ndarray:
        return np.bincount(self.terms, values, v)


def flat_chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(doc ids, owner, terms, counts) of the bags in a partition, DOCS_AT_ONCE at a time, without Python objects."""
    for whole in batches:
        for at in range(0, whole.num_rows, DOCS_AT_ONCE):
            batch = whole.slice(at, DOCS_AT_ONCE)
            terms, counts = batch.column("terms"), batch.column("counts")
            sizes = np.diff(terms.offsets.to_numpy())
            yield batch.column("doc_id").to_numpy(zero_copy_only=False), np.repeat(np.arange(batch.num_rows), sizes), terms.flatten().to_numpy(zero_copy_only=False), counts.flatten().to_numpy(zero_copy_only=False)


def node_chunk(owner: np.ndarray, terms: np.ndarray, counts: np.ndarray, omega: np.ndarray | None, min_len: float) -> Chunk:
    """The entries that a node keeps; documents below min_len leave."""
    weight = np.ones(len(terms)) if omega is None else omega[terms]
    scaled = counts * weight
    length = np.bincount(owner, scaled) if len(owner) else np.zeros(0)
    kept = length >= min_len
    number = np.cumsum(kept) - 1
    at = kept[owner] & (scaled > 0)
    return Chunk(number[owner[at]], terms[at], scaled[at], weight[at], length[kept])


Weights = dict[str, np.ndarray | None]


def _scan(bags: DataFrame, kernel: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], ddl: str) -> DataFrame:
    ship(bags.sparkSession)
    return bags.select("doc_id", "len", "terms", "counts").mapInArrow(kernel, ddl)


def self_pairs(chunk: Chunk, how: str) -> np.ndarray:
    """What is taken off the diagonal: the counts themselves, or thinned by the word's weight."""
    return chunk.counts * chunk.omega if how == "thinned" else chunk.counts


def add_pairs(block: np.ndarray, chunk: Chunk, scale: np.ndarray, self_pair: str) -> None:
    """Adds a chunk's scaled pair counts to a dense block: document by document where they are sparse, else as one product."""
    v = len(block)
    value = chunk.counts * np.sqrt(scale)[chunk.owner]
    sizes = np.bincount(chunk.owner, minlength=chunk.n).astype(float)
    if 2e-5 * chunk.n + 4e-9 * (sizes**2).sum() < 2e-10 * chunk.n * v * v:
        edges = np.concatenate([[0], np.cumsum(sizes)]).astype(int)
        flat = block.reshape(-1)
        for d in range(chunk.n):
            own = slice(edges[d], edges[d + 1])
            t, c = chunk.terms[own].astype(np.int64), value[own]
            flat[(t[:, None] * v + t).ravel()] += np.outer(c, c).ravel()
    else:
        matrix = np.zeros((chunk.n, v))
        matrix[chunk.owner, chunk.terms] = value
        block += matrix.T @ matrix
    at = np.arange(v)
    block[at, at] -= chunk.by_term(self_pairs(chunk, self_pair) * scale[chunk.owner], v)


def level_moments(bags: DataFrame, v: int, weights: Weights | None = None, *, min_len: float = MIN_LEN, self_pair: str = "plain", pairs: bool = True, ledger=None) -> DataFrame:
    """path, x1, x2, total: unnormalised sums; one scan for as many nodes as BLOCK_BYTES of weights allow.

    x1 <= x2: second-moment numerators.  x2 = -1: first-moment numerators.  x1 = x2 = -1: the number of documents.
    """
    weights = {"o": None} if weights is None else weights
    groups = group_nodes(list(weights), 8 * v, BLOCK_BYTES)
    if ledger is not None:
        ledger.scans += len(groups)
    return reduce(DataFrame.union, [_level_moments(bags, v, {p: weights[p] for p in names}, min_len, self_pair, pairs) for names in groups])


def _level_moments(bags: DataFrame, v: int, weights: Weights, min_len: float, self_pair: str, pairs: bool) -> DataFrame:
    sent = bags.sparkSession.sparkContext.broadcast(weights)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = sent.value
        dense = len(known) * v * v * 8 <= BLOCK_BYTES
        first = {p: np.zeros(v) for p in known}
        n_docs = dict.fromkeys(known, 0)
        block = {p: np.zeros((v, v)) for p in known} if dense and pairs else {}
        held: dict[str, list[tuple[np.ndarray, np.ndarray]]] = {p: [] for p in known}
        size = 0

        def rows(path: str, x1: np.ndarray, x2: np.ndarray, total: np.ndarray) -> Iterator[pa.RecordBatch]:
            for at in range(0, len(x1), 500_000):
                part = slice(at, at + 500_000)
                n = len(x1[part])
                yield pa.RecordBatch.from_arrays([pa.array([path] * n, pa.string()), pa.array(x1[part], pa.int32()), pa.array(x2[part], pa.int32()), pa.array(total[part], pa.float64())], ["path", "x1", "x2", "total"])

        def flush() -> Iterator[pa.RecordBatch]:
            for path, parts in held.items():
                if parts:
                    key, place = np.unique(np.concatenate([k for k, _ in parts]), return_inverse=True)
                    total = np.bincount(place, np.concatenate([x for _, x in parts]), len(key))
                    yield from rows(path, (key // v).astype(np.int32), (key % v).astype(np.int32), total)
                    parts.clear()

        for _, owner, terms, counts in flat_chunks(batches):
            for path, omega in known.items():
                chunk = node_chunk(owner, terms, counts, omega, min_len)
                if not chunk.n:
                    continue
                n_docs[path] += chunk.n
                first[path] += chunk.by_term(chunk.counts / chunk.length[chunk.owner], v)
                if not pairs:
                    continue
                scale = 1 / (chunk.length * (chunk.length - 1))
                if dense:
                    add_pairs(block[path], chunk, scale, self_pair)
                else:
                    edges = np.searchsorted(chunk.owner, np.arange(chunk.n + 1))
                    off = self_pairs(chunk, self_pair)
                    for d in range(chunk.n):
                        own = slice(edges[d], edges[d + 1])
                        t, c = chunk.terms[own].astype(np.int64), chunk.counts[own]
                        i, j = np.triu_indices(len(t))
                        value = c[i] * c[j]
                        value[i == j] -= off[own]
                        held[path].append((np.minimum(t[i], t[j]) * v + np.maximum(t[i], t[j]), value * scale[d]))
                        size += len(i)
                        if size > PAIRS_HELD:
                            yield from flush()
                            size = 0
        yield from flush()
        for path in known:
            if n_docs[path]:
                yield from rows(path, np.array([-1]), np.array([-1]), np.array([float(n_docs[path])]))
                x = np.flatnonzero(first[path])
                yield from rows(path, x, np.full(len(x), -1), first[path][x])
                if dense and pairs:
                    x1, x2 = np.nonzero(np.triu(block[path]))
                    yield from rows(path, x1, x2, block[path][x1, x2])

    return _scan(bags, kernel, "path string, x1 int, x2 int, total double").groupBy("path", "x1", "x2").agg(F.sum("total").alias("total"))


@dataclass
class NodeMoments:
    """Normalised moments of one node on the driver."""

    n_docs: float
    m1: np.ndarray
    e2: np.ndarray  # dense and symmetric


def first_moment(bags: DataFrame, v: int, weights: Weights | None = None, **options) -> DataFrame:
    """path, x, v."""
    sums = level_moments(bags, v, weights, pairs=False, **options)
    docs = sums.where("x1 = -1").select("path", F.col("total").alias("d"))
    return sums.where("x1 >= 0").join(F.broadcast(docs), "path").select("path", F.col("x1").alias("x"), (F.col("total") / F.col("d")).alias("v"))


def second_moment(bags: DataFrame, v: int, weights: Weights | None = None, **options) -> DataFrame:
    """path, x1 <= x2, v, zero entries dropped."""
    sums = level_moments(bags, v, weights, **options)
    docs = sums.where("x1 = -1").select("path", F.col("total").alias("d"))  # one row for each node
    return sums.where("x2 >= 0 and abs(total) > 1e-15").join(F.broadcast(docs), "path").select("path", "x1", "x2", (F.col("total") / F.col("d")).alias("v"))


def second_moment_sql(long_bags: DataFrame, *, min_len: float = MIN_LEN) -> DataFrame:
    """The root's second moment by a self-join of (doc_id, term_id, c): for small vocabularies and as a check."""
    lengths = long_bags.groupBy("doc_id").agg(F.sum("c").alias("l")).where(F.col("l") >= min_len)
    kept = long_bags.join(lengths, "doc_id")
    a, b = kept.select("doc_id", "l", F.col("term_id").alias("x1"), F.col("c").alias("c1")), kept.select("doc_id", F.col("term_id").alias("x2"), F.col("c").alias("c2"))
    value = (F.col("c1") * F.col("c2") - F.when(F.col("x1") == F.col("x2"), F.col("c1")).otherwise(0)) / (F.col("l") * (F.col("l") - 1))
    pairs = a.join(b, "doc_id").where("x1 <= x2").groupBy("x1", "x2").agg(F.sum(value).alias("total"))
    return pairs.where("total > 0").crossJoin(F.broadcast(lengths.agg(F.count("*").alias("d")))).select("x1", "x2", (F.col("total") / F.col("d")).alias("v"))


#: Rows of a dense second moment that travel together.
ROWS_TOGETHER = 64


def moments_of(bags: DataFrame, v: int, weights: Weights | None = None, *, min_len: float = MIN_LEN, self_pair: str = "plain", ledger=None) -> dict[str, NodeMoments]:
    """Every node's moments on the driver, E2 dense: for vocabularies whose v * v block is small.

    Tasks hand on blocks of rows of their dense sums as bytes, keyed by node and block; the receiving tasks add them up
    in numpy and the driver gets each block once.
    """
    weights = {"o": None} if weights is None else weights
    guard(v, 2, int((BLOCK_BYTES / 8) ** 0.5))
    out: dict[str, NodeMoments] = {}
    for names in group_nodes(list(weights), 8 * v * v, 4 * BLOCK_BYTES):  # nodes beyond what a task and the driver may hold at once take another scan
        if ledger is not None:
            ledger.scans += 1
        out |= _moments_at_once(bags, v, {p: weights[p] for p in names}, min_len, self_pair)
    return out


PAYLOADS = "path string, part bigint, payload binary"


def _added(payloads: DataFrame) -> DataFrame:
    """The arrays of float64 that share path and part, added up in numpy by the receiving tasks."""

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[tuple[str, int], np.ndarray] = {}
        for b in batches:
            for path, part, payload in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2), strict=True):
                own = np.frombuffer(payload.as_buffer(), np.float64)
                if (path, part) in sums:
                    sums[path, part] += own
                else:
                    sums[path, part] = own.copy()
        for (path, part), total in sums.items():
            yield pa.RecordBatch.from_arrays([pa.array([path]), pa.array([part]), pa.array([total.tobytes()])], ["path", "part", "payload"])

    return payloads.repartition("path", "part").mapInArrow(add, PAYLOADS)


def _moments_at_once(bags: DataFrame, v: int, weights: Weights, min_len: float, self_pair: str) -> dict[str, NodeMoments]:
    sent = bags.sparkSession.sparkContext.broadcast(weights)
    names = ["path", "part", "payload"]  # of PAYLOADS

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = sent.value
        head = {p: np.zeros(v + 1) for p in known}
        block = {p: np.zeros((v, v)) for p in known}
        for _, owner, terms, counts in flat_chunks(batches):
            for path, omega in known.items():
                chunk = node_chunk(owner, terms, counts, omega, min_len)
                if chunk.n:
                    head[path][v] += chunk.n
                    head[path][:v] += chunk.by_term(chunk.counts / chunk.length[chunk.owner], v)
                    add_pairs(block[path], chunk, 1 / (chunk.length * (chunk.length - 1)), self_pair)
        for path in known:
            if head[path][v]:
                yield pa.RecordBatch.from_arrays([pa.array([path]), pa.array([-1]), pa.array([head[path].tobytes()])], names)
                for k in range(0, v, ROWS_TOGETHER):
                    yield pa.RecordBatch.from_arrays([pa.array([path]), pa.array([k]), pa.array([block[path][k : k + ROWS_TOGETHER, k:].tobytes()])], names)

    rows = _added(_scan(bags, kernel, PAYLOADS)).collect()
    found: dict[str, NodeMoments] = {}
    for r in rows:
        if r.part == -1:
            head = np.frombuffer(r.payload)
            found[r.path] = NodeMoments(float(head[v]), head[:v] / head[v], np.zeros((v, v)))
    for r in rows:
        if r.part >= 0:
            n = min(ROWS_TOGETHER, v - r.part)
            found[r.path].e2[r.part : r.part + n, r.part :] = np.frombuffer(r.payload).reshape(n, v - r.part) / found[r.path].n_docs
    for m in found.values():
        upper = np.triu(m.e2)
        m.e2 = upper + np.triu(upper, 1).T
    return found


def second_moment_apply(bags: DataFrame, v: int, q: dict[str, np.ndarray], weights: Weights | None = None, *, min_len: float = MIN_LEN, self_pair: str = "plain") -> DataFrame:
    """path, x, y (array): E2 times Q for every node in one scan; no pair is ever formed.  x = -1 carries the documents."""
    weights = dict.fromkeys(q) if weights is None else weights
    sent = bags.sparkSession.sparkContext.broadcast((q, weights))
    width = next(iter(q.values())).shape[1]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        maps, known = sent.value
        sums = {p: np.zeros((v, width)) for p in known}
        n_docs = dict.fromkeys(known, 0)
        for _, owner, terms, counts in flat_chunks(batches):
            for path, omega in known.items():
                chunk = node_chunk(owner, terms, counts, omega, min_len)
                if not chunk.n:
                    continue
                n_docs[path] += chunk.n
                scale = (1 / (chunk.length * (chunk.length - 1)))[chunk.owner]
                rows = maps[path][chunk.terms]
                whole = chunk.by_doc(chunk.counts[:, None] * rows)
                gain = scale[:, None] * (chunk.counts[:, None] * whole[chunk.owner] - self_pairs(chunk, self_pair)[:, None] * rows)
                for j in range(width):
                    sums[path][:, j] += chunk.by_term(gain[:, j], v)
        for path in known:
            if n_docs[path]:
                x = np.flatnonzero(np.abs(sums[path]).any(axis=1))
                ids = np.append(x, -1).astype(np.int32)
                values = np.vstack([sums[path][x], np.full((1, width), float(n_docs[path]))])
                yield pa.RecordBatch.from_arrays([pa.array([path] * len(ids), pa.string()), pa.array(ids), pa.array(list(values), pa.list_(pa.float64()))], ["path", "x", "part"])

    parts = _scan(bags, kernel, "path string, x int, part array<double>")
    return parts.groupBy("path", "x").agg(*(F.sum(F.col("part")[j]).alias(f"y{j}") for j in range(width))).select("path", "x", F.array(*(f"y{j}" for j in range(width))).alias("y"))


def applied(rows: DataFrame, v: int, width: int) -> dict[str, tuple[float, np.ndarray]]:
    """second_moment_apply on the driver: (documents, E2 Q) of each node."""
    out: dict[str, tuple[float, np.ndarray]] = {}
    for path, own in rows.toPandas().groupby("path"):
        x, y = own["x"].to_numpy(), np.vstack(own["y"].to_numpy())
        d = float(y[x == -1][0, 0])
        full = np.zeros((v, width))
        full[x[x >= 0]] = y[x >= 0] / d
        out[path] = d, full
    return out


DENSE_THIRD_WORDS = 300


class VocabularyTooLarge(MemoryError):
    """A dense tensor over the vocabulary would not fit."""


def guard(v: int, power: int, most: int) -> None:
    if v > most:
        raise VocabularyTooLarge(f"a dense V^{power} array for V = {v} takes {8 * v**power / 1e9:.3g} GB; the limit is V = {most}")


def third_moment_dense(bags: DataFrame, v: int, *, min_len: float = MIN_LEN) -> np.ndarray:
    """E3 as a V x V x V array, distinct triples of tokens, small V only.

    E3 is symmetric: of each first word x tasks hand on the square of words from x on, as bytes.  The receiving tasks add
    the squares up.
    """
    guard(v, 3, DENSE_THIRD_WORDS)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        squares, n = [np.zeros((v - x, v - x)) for x in range(v)], 0
        for _, owner, terms, counts in flat_chunks(batches):
            chunk = node_chunk(owner, terms, counts, None, min_len)
            if not chunk.n:
                continue
            n += chunk.n
            c = np.zeros((chunk.n, v))
            c[chunk.owner, chunk.terms] = chunk.counts
            scale = 1 / (chunk.length * (chunk.length - 1) * (chunk.length - 2))
            for x in np.unique(chunk.terms):
                own = np.flatnonzero(c[:, x])
                first, rest = c[own, x], c[own, x:]
                once = scale[own] * first
                square = (rest * once[:, None]).T @ rest  # what repeats a word is put right below, without differences of sums
                at = np.arange(v - x)
                square[at, at] = once @ (rest * (rest - 1))
                square[0] = square[:, 0] = (once * (first - 1)) @ rest
                square[0, 0] = (once * (first - 1)) @ (first - 2)
                squares[x] += square
        if n:
            for x, total in [(-1, np.array([float(n)])), *enumerate(squares)]:
                yield pa.RecordBatch.from_arrays([pa.array(["o"]), pa.array([x]), pa.array([total.tobytes()])], ["path", "part", "payload"])

    summed = {r.part: np.frombuffer(r.payload) for r in _added(_scan(bags, kernel, PAYLOADS)).collect()}
    out = np.zeros((v, v, v))
    for x in range(v if summed else 0):
        out[x, x:, x:] = out[x:, x, x:] = out[x:, x:, x] = summed[x].reshape(v - x, v - x) / summed[-1][0]
    return out


@dataclass
class CoreParts:
    """Sums over a node's documents from which the core follows (see tensor.core_from)."""

    n_docs: float
    p1: np.ndarray
    p2: np.ndarray
    g: np.ndarray


def project_third(bags: DataFrame, v: int, w: dict[str, np.ndarray], weights: Weights | None = None, *, min_len: float = MIN_LEN, self_pair: str = "plain", ledger=None) -> dict[str, CoreParts]:
    """One scan for all nodes (that BLOCK_BYTES of maps allow): their k^3 sums and per-word sums; time is linear in tokens, the shuffle carries k^3 + V sums."""
    weights = dict.fromkeys(w) if weights is None else weights
    out: dict[str, CoreParts] = {}
    for names in group_nodes(list(w), 8 * v * (1 + max(m.shape[1] for m in w.values())), BLOCK_BYTES):
        if ledger is not None:
            ledger.scans += 1
        out |= _project_third(bags, v, {p: w[p] for p in names}, {p: weights[p] for p in names}, min_len, self_pair)
    return out


def _project_third(bags: DataFrame, v: int, w: dict[str, np.ndarray], weights: Weights, min_len: float, self_pair: str) -> dict[str, CoreParts]:
    sent = bags.sparkSession.sparkContext.broadcast((w, weights))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        maps, known = sent.value
        sums = {p: [np.zeros((m.shape[1],) * 3), np.zeros((m.shape[1],) * 3), np.zeros(v)] for p, m in maps.items()}
        n_docs = dict.fromkeys(known, 0)
        for _, owner, terms, counts in flat_chunks(batches):
            for path, omega in known.items():
                chunk = node_chunk(owner, terms, counts, omega, min_len)
                if not chunk.n:
                    continue
                n_docs[path] += chunk.n
                length = chunk.length
                scale = 1 / (length * (length - 1) * (length - 2))
                rows = maps[path][chunk.terms]
                k = rows.shape[1]
                pair_count = self_pairs(chunk, self_pair)
                y = chunk.by_doc(chunk.counts[:, None] * rows)
                inner = chunk.by_doc((pair_count[:, None, None] * rows[:, :, None] * rows[:, None, :]).reshape(-1, k * k)).reshape(-1, k, k)
                sums[path][0] += np.einsum("d,di,dj,dl->ijl", scale, y, y, y, optimize=True)
                sums[path][1] += np.einsum("d,di,djl->ijl", scale, y, inner, optimize=True)
                once = chunk.counts * chunk.omega**2 if self_pair == "thinned" else chunk.counts
                sums[path][2] += chunk.by_term(once * scale[chunk.owner], v)
        for path, parts in sums.items():
            if n_docs[path]:
                flat = np.concatenate([[float(n_docs[path])], parts[0].ravel(), parts[1].ravel(), parts[2]])
                at = np.flatnonzero(flat)
                yield pa.RecordBatch.from_arrays([pa.array([path] * len(at), pa.string()), pa.array(at), pa.array(flat[at])], ["path", "at", "total"])

    summed = _scan(bags, kernel, "path string, at bigint, total double").groupBy("path", "at").agg(F.sum("total").alias("total")).toPandas()
    out = {}
    for path, own in summed.groupby("path"):
        k = w[path].shape[1]
        flat = np.zeros(1 + 2 * k**3 + v)
        flat[own["at"].to_numpy()] = own["total"].to_numpy()
        out[path] = CoreParts(flat[0], flat[1 : 1 + k**3].reshape(k, k, k), flat[1 + k**3 : 1 + 2 * k**3].reshape(k, k, k), flat[1 + 2 * k**3 :])
    return out

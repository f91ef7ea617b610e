"""Quality classifier: a factorisation machine over hashed words, structure statistics and metadata.

score = sigmoid(b + sum_j w_j x_j + 1/2 sum_f [(sum_j v_jf x_j)^2 - sum_j v_jf^2 x_j^2]): the pairwise interactions of
all features in time linear in the features present.  Labels, language, source and ids are never inputs.

Defined results: null text counts as empty (structure statistics all zero); a null n_chars counts as 0; empty and
very long texts are scored whole; equal rows get equal scores; without labels of both classes every score is 0.5.
Columns of docs other than doc_id, text and n_chars are ignored, whatever their names.
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from momenttree.llm import labelled
from momenttree.llm.runtime import ship

WORD_BUCKETS = 1 << 15
STATISTICS = 20
WIDTH = WORD_BUCKETS + STATISTICS
FACTORS = 6
#: At most so many labelled rows teach; classes keep their shares.
TRAINING_ROWS = 6_000
EPOCHS = 10
THRESHOLD = 0.7


def features(text: str, n_chars: float | None) -> tuple[np.ndarray, np.ndarray]:
    """(indices, values): word buckets with log-scaled shares, then the statistics.

    Statistics: text length, word count, declared length; mean word length; shares of distinct words, of the commonest word, of words
    equal to the one before, of short and long words; shares of capitals, digits, white space, ASCII punctuation,
    bars, other bytes; line count, repeated lines, characters a line; shares of words that end in punctuation or start with a capital.
    """
    words = text.split()
    n = len(words)
    stats = np.zeros(STATISTICS)
    raw = np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)
    stats[2] = np.log1p(max(n_chars or 0.0, 0.0)) / 10
    if not n:
        return np.arange(WORD_BUCKETS, WIDTH), stats
    counts = Counter(text.lower().split())
    lengths = np.fromiter(map(len, words), np.int64, n)
    histogram = np.bincount(raw, minlength=256) / len(raw)
    lines = [x for x in text.split("\n") if x]
    stats[0], stats[1] = np.log1p(len(text)) / 10, np.log1p(n) / 10
    stats[3] = min(lengths.mean() / 10, 3)
    stats[4] = len(counts) / n
    stats[5] = max(counts.values()) / n
    stats[6] = sum(map(str.__eq__, words[1:], words)) / n
    stats[7], stats[8] = (lengths <= 3).mean(), (lengths >= 12).mean()
    stats[9], stats[10] = histogram[65:91].sum(), histogram[48:58].sum() * 5
    stats[11] = histogram[[9, 10, 13, 32]].sum()
    stats[12] = (histogram[33:48].sum() + histogram[58:65].sum() + histogram[91:97].sum() + histogram[123:127].sum()) * 3
    stats[13], stats[14] = min(histogram[124] * 20, 3), histogram[128:].sum()
    stats[15] = np.log1p(len(lines)) / 5
    stats[16] = 1 - len(set(lines)) / max(len(lines), 1)
    stats[17] = np.log1p(len(text) / max(len(lines), 1)) / 10
    stats[18] = sum(not w[-1].isalnum() for w in words) / n
    stats[19] = sum(map(str.isupper, (w[0] for w in words))) / n
    buckets: Counter = Counter()
    for word, c in counts.items():
        buckets[zlib.crc32(word.encode("utf-8", "surrogatepass")) & (WORD_BUCKETS - 1)] += c
    index = np.fromiter(buckets.keys(), np.int64, len(buckets))
    value = np.fromiter(buckets.values(), np.float64, len(buckets))
    value = np.log1p(value)
    value /= np.sqrt((value * value).sum())
    return np.concatenate([index, np.arange(WORD_BUCKETS, WIDTH)]), np.concatenate([value, stats])


@dataclass
class FactorMachine:
    """b, w (features) and v (features x factors)."""

    b: float
    w: np.ndarray
    v: np.ndarray
    trained: bool = True

    def logit(self, index: np.ndarray, value: np.ndarray) -> float:
        vx = self.v[index] * value[:, None]
        return float(self.b + self.w[index] @ value + 0.5 * ((vx.sum(axis=0) ** 2) - (vx * vx).sum(axis=0)).sum())

    def score(self, index: np.ndarray, value: np.ndarray) -> float:
        return float(1 / (1 + np.exp(-np.clip(self.logit(index, value), -30, 30)))) if self.trained else 0.5


def fit(rows: list[tuple[np.ndarray, np.ndarray]], y: np.ndarray, *, factors: int = FACTORS, epochs: int = EPOCHS, rate: float = 0.1, shrink: float = 1e-5, seed: int = 7) -> FactorMachine:
    """Logistic loss by mini-batches with per-weight steps (AdaGrad)."""
    random = np.random.default_rng(seed)
    b, w, v = 0.0, np.zeros(WIDTH), random.normal(0, 0.05, (WIDTH, factors))
    if len(y) == 0 or y.min() == y.max():
        return FactorMachine(b, w, v, trained=False)
    b = float(np.log(y.mean() / (1 - y.mean())))
    gb, gw, gv = 1e-3, np.full(WIDTH, 1e-3), np.full((WIDTH, factors), 1e-3)
    for _ in range(epochs):
        order = random.permutation(len(y))
        for at in range(0, len(y), 64):
            batch = order[at : at + 64]
            index = np.concatenate([rows[i][0] for i in batch])
            value = np.concatenate([rows[i][1] for i in batch])
            sizes = np.array([len(rows[i][0]) for i in batch])
            starts, owner = np.concatenate([[0], np.cumsum(sizes)[:-1]]), np.repeat(np.arange(len(batch)), sizes)
            vx = v[index] * value[:, None]
            sums = np.add.reduceat(vx, starts)
            logit = b + np.add.reduceat(w[index] * value, starts) + 0.5 * (sums**2 - np.add.reduceat(vx * vx, starts)).sum(axis=1)
            error = (1 / (1 + np.exp(-np.clip(logit, -30, 30))) - y[batch]) / len(batch)
            step_w = error[owner] * value
            step_v = step_w[:, None] * (sums[owner] - vx)
            touched, place = np.unique(index, return_inverse=True)
            dw = np.bincount(place, step_w, len(touched)) + shrink * w[touched]
            dv = np.stack([np.bincount(place, step_v[:, f], len(touched)) for f in range(factors)], axis=1) + shrink * v[touched]
            gw[touched] += dw * dw
            gv[touched] += dv * dv
            w[touched] -= rate * dw / np.sqrt(gw[touched])
            v[touched] -= rate * dv / np.sqrt(gv[touched])
            db = error.sum()
            gb += db * db
            b -= rate * db / np.sqrt(gb)
    return FactorMachine(b, w.astype(np.float32), v.astype(np.float32))


def _columns(docs: DataFrame) -> DataFrame:
    n_chars = F.col("n_chars").cast("double") if "n_chars" in docs.columns else F.lit(None).cast("double")
    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text"), n_chars.alias("n_chars"))


def train(docs: DataFrame, labels: DataFrame, *, bound: int = TRAINING_ROWS) -> FactorMachine:
    """Fitted on at most `bound` labelled rows outside the held-out fold; features are made on the executors."""
    ship(docs.sparkSession)
    rows = labelled.sample(docs, labels, "quality", labelled.fold(4) != 2, bound)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            made = [features(t or "", c) for t, c in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(3), pa.array([i.astype(np.int32).tobytes() for i, _ in made], pa.binary()), pa.array([x.astype(np.float32).tobytes() for _, x in made], pa.binary())], ["doc_id", "y", "i", "x"])

    found = sorted(rows.select("doc_id", "text", "n_chars", "y").mapInArrow(run, "doc_id bigint, y int, i binary, x binary").collect())
    return fit([(np.frombuffer(r.i, np.int32), np.frombuffer(r.x, np.float32).astype(np.float64)) for r in found], np.array([r.y for r in found], np.float64))


def score(docs: DataFrame, model: FactorMachine) -> DataFrame:
    """doc_id, score.  One scan, no shuffle; the model has a fixed size (about 1 MB)."""
    spark = docs.sparkSession
    ship(spark)
    sent = spark.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = sent.value
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                part = batch.slice(at, 1000)
                scores = [known.score(*features(t or "", c)) for t, c in zip(part.column(1).to_pylist(), part.column(2).to_pylist(), strict=True)]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(scores, pa.float64())], ["doc_id", "score"])

    return _columns(docs).mapInArrow(run, "doc_id bigint, score double")


def judge(docs: DataFrame, labels: DataFrame, *, bound: int = TRAINING_ROWS) -> DataFrame:
    """doc_id, held_out, score, predicted."""
    scored = score(docs, train(docs, labels, bound=bound))
    return scored.select("doc_id", (labelled.fold(4) == 2).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, labels: DataFrame, *, bound: int = TRAINING_ROWS) -> DataFrame:
    """The rows of docs that the classifier accepts; without labels of both classes all stay.

    The score is appended to the very rows it judges, so nothing is shuffled or joined.
    """
    model = train(docs, labels, bound=bound)
    if not model.trained:
        return docs
    spark = docs.sparkSession
    sent = spark.sparkContext.broadcast(model)
    names = docs.columns
    text_at, chars_at = names.index("text"), names.index("n_chars") if "n_chars" in names else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = sent.value
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                part = batch.slice(at, 1000)
                chars = part.column(chars_at).to_pylist() if chars_at is not None else [None] * part.num_rows
                yield part.filter(pa.array([known.score(*features(t or "", c)) >= THRESHOLD for t, c in zip(part.column(text_at).to_pylist(), chars, strict=True)], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)

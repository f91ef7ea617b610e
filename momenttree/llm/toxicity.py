"""Toxic passages: maximum-scoring segments over token log-odds, calibrated by extreme values.

Each token has the log-odds of its form between toxic and clean rows under an informative Dirichlet prior; a
form is the word or one of its leading stems, and only significant forms (z of at least Z_LEAST) score above the
constant penalty that all tokens pay (negative log-odds as scores found no more toxic rows and gave more false alarms).
One linear scan finds every maximal-scoring segment of a text.  A segment of score S in n tokens has
E = K n exp(-lambda S) expected equals in clean text: lambda is the positive root of the moment equation of the scores of
clean tokens, K the likeliest value given the best segments of the clean rows.  Segments with a small E are the toxic
passages.  Several segments, each of them unremarkable, count together: the sum of the r best ones has a known tail too,
and the least probable r, with the best segment, gives a text's probability.

Defined results: null text counts as empty; a text without scoring tokens has no passage and the lowest score;
equal rows get equal scores; without labels of both classes, or if no form is significant, every score is 0.0.
Other columns of docs are ignored.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from momenttree.llm import labelled
from momenttree.llm.runtime import cut, ship, text_batches

TOKENS = re.compile(r"\w+").findall
STEMS = (6, 5, 4)
#: At most so many labelled rows teach.
TRAINING_ROWS = 10_000
#: Weight of the prior as a share of the tokens counted.
PRIOR_SHARE = 0.02
Z_LEAST = 1.8
#: A form has to occur in so many toxic rows of the sample.
ROWS_LEAST = 5
PENALTY = 0.15
SCORE_MOST = 6.0
SIGNIFICANT = 0.05
CACHE_ENTRIES = 400_000


def forms(token: str) -> list[str]:
    """The word itself (marked as whole) and its leading stems, longest first."""
    return [token + "$"] + [token[:k] for k in STEMS if len(token) >= k]


def segments(scores: list[tuple[int, float]], penalty: float) -> list[tuple[float, int, int]]:
    """All maximal-scoring segments (score, first, last token) of a sequence given as its positive positions.

    Tokens between positive ones cost `penalty` each.  Linear: each candidate is pushed once and merged at most once;
    a candidate looks back only past candidates whose left sums are not smaller, and merging removes these.
    """
    stack: list[tuple[float, float, int, int, int]] = []  # left sum, right sum, first, last, index of the nearest smaller left sum
    total, at = 0.0, 0
    for position, gain in scores:
        left = total - penalty * (position - at)
        right = left + gain
        total, at = right, position + 1
        first, last = position, position
        while True:
            j = len(stack) - 1
            while j >= 0 and stack[j][0] >= left:
                j = stack[j][4]
            if j < 0 or stack[j][1] >= right:
                stack.append((left, right, first, last, j))
                break
            left, first = stack[j][0], stack[j][2]
            del stack[j:]
    return [(r - a, f, z) for a, r, f, z, _ in stack]


def evidence_of(n: int, scores: list[float], rate: float, spread: float) -> tuple[float, float]:
    """See ToxicModel.evidence.  With t = rate * (sum of the r best) - r ln(K n), the tail of that sum is about
    exp(-t) t^(r-1) / (r! (r-1)!); -ln of it is largest at the r that is least likely in clean text.
    """
    if not scores:
        return 0.0, 0.0
    base = math.log(max(spread * max(n, 1), 1e-9))
    total, most = 0.0, 0.0
    for r, s in enumerate(sorted(scores, reverse=True), 1):
        total += rate * s
        t = total - r * base
        if t > r:
            most = max(most, t - (r - 1) * math.log(t) + math.lgamma(r + 1) + math.lgamma(r))
    return max(0.0, rate * max(scores) - base) / 10, math.log1p(most)


@dataclass
class ToxicModel:
    weights: dict[str, float] = field(default_factory=dict)
    rate: float = 1.0  # lambda
    spread: float = 1.0  # K
    bias: float = 0.0
    slopes: tuple[float, float] = (0.0, 0.0)
    trained: bool = False
    penalty: float = PENALTY

    def __post_init__(self):
        self.cache: dict[str, float] = {}

    def __getstate__(self):
        return self.__dict__ | {"cache": {}}

    def weight(self, token: str) -> float:
        found = self.cache.get(token)
        if found is None:
            found = next((w for f in forms(token) if (w := self.weights.get(f)) is not None), 0.0)
            if len(self.cache) >= CACHE_ENTRIES:
                self.cache.clear()
            self.cache[token] = found
        return found

    def scored(self, text: str) -> tuple[int, list[tuple[float, int, int]]]:
        """Token count and every segment as (score, first, last token)."""
        tokens = TOKENS(text.lower())
        penalty = self.penalty
        positive = [(k, w - penalty) for k, w in enumerate(map(self.weight, tokens)) if w > penalty]
        return len(tokens), segments(positive, penalty) if positive else []

    def passages(self, text: str) -> tuple[int, list[tuple[float, int, int]]]:
        """Token count and every segment as (expected count in clean text, first, last token)."""
        n, found = self.scored(text)
        return n, [(self.expected(s, n), a, b) for s, a, b in found]

    def expected(self, score: float, n: int) -> float:
        return self.spread * max(n, 1) * math.exp(-self.rate * score)

    def evidence(self, text: str) -> tuple[float, float]:
        """(best, together): -ln E of the best segment in tens of nats, and the logarithm of the sums' evidence."""
        n, found = self.scored(text)
        return evidence_of(n, [s for s, _, _ in found], self.rate, self.spread)

    def score(self, text: str) -> float:
        if not self.trained:
            return 0.0
        return self.probability(self.evidence(text))

    def probability(self, evidence: tuple[float, float]) -> float:
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, self.bias + self.slopes[0] * evidence[0] + self.slopes[1] * evidence[1]))))


def log_odds(toxic: Counter, clean: Counter, n_toxic: int, n_clean: int) -> dict[str, tuple[float, float]]:
    """Form -> (log-odds ratio, z) with prior counts in proportion to the form's share of all tokens."""
    found = {}
    weight = PRIOR_SHARE * (n_toxic + n_clean)
    for form, a in toxic.items():
        b = clean.get(form, 0)
        prior = PRIOR_SHARE * (a + b)
        odds = math.log((a + prior) / max(n_toxic + weight - a - prior, 1e-9)) - math.log((b + prior) / max(n_clean + weight - b - prior, 1e-9))
        found[form] = odds, odds / math.sqrt(1 / (a + prior) + 1 / (b + prior))
    return found


def moment_root(clean_scores: np.ndarray, shares: np.ndarray) -> float:
    """The positive root of sum share * exp(root * score) = 1, or a large rate if no score is positive."""
    if not (clean_scores > 0).any() or clean_scores @ shares >= 0:
        return 1.0
    low, high = 0.0, 1.0
    excess = lambda r: float(shares @ np.exp(np.minimum(r * clean_scores, 500))) - 1
    while excess(high) < 0 and high < 64:
        high *= 2
    low = high / 2 if high > 1 else 1e-9
    for _ in range(60):
        mid = (low + high) / 2
        low, high = (mid, high) if excess(mid) < 0 else (low, mid)
    return low


def _count_rows(batches: Iterator[pa.RecordBatch], wanted: frozenset | None) -> Iterator[pa.RecordBatch]:
    """(form, occurrences, rows) sums of a partition; the form '' counts tokens."""
    uses, rows = Counter(), Counter()
    for _, texts in text_batches(batches):
        for text in texts:
            tokens = TOKENS(text.lower())
            own = Counter()
            for token, c in Counter(tokens).items():
                for form in forms(token):
                    if wanted is None or form in wanted:
                        own[form] += c
            uses.update(own)
            rows.update(own.keys())
            uses[""] += len(tokens)
            rows[""] += 1
    if rows:
        keys = list(uses)
        yield pa.RecordBatch.from_arrays([pa.array(keys, pa.string()), pa.array([uses[k] for k in keys], pa.int64()), pa.array([rows[k] for k in keys], pa.int64())], ["form", "n", "n_rows"])


def _counts(rows: DataFrame, wanted: frozenset | None, least: int) -> dict[str, tuple[int, int]]:
    made = rows.select("doc_id", "text").mapInArrow(lambda batches: _count_rows(batches, wanted), "form string, n bigint, n_rows bigint")
    summed = made.groupBy("form").agg(F.sum("n").alias("n"), F.sum("n_rows").alias("n_rows")).where((F.col("n_rows") >= least) | (F.col("form") == ""))
    return {r.form: (r.n, r.n_rows) for r in summed.collect()}


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 0.05, steps: int = 40) -> np.ndarray:
    """Bias and slopes by Newton steps with a ridge on the slopes."""
    x = np.column_stack([np.ones(len(x)), x])
    beta = np.zeros(x.shape[1])
    penalty = np.diag([1e-6] + [ridge] * (x.shape[1] - 1))
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ beta, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + penalty, x.T @ (y - p) - penalty @ beta)
        beta += step
        if np.abs(step).max() < 1e-8:
            break
    return beta


def train(docs: DataFrame, labels: DataFrame, *, bound: int = TRAINING_ROWS) -> ToxicModel:
    """Fitted on at most `bound` labelled rows outside the held-out fold.

    What reaches the driver is bounded with the sample: forms of at least ROWS_LEAST of its toxic rows, then their
    counts in its clean rows, then the scores of each row's segments.
    """
    ship(docs.sparkSession)
    rows = cut(labelled.sample(docs, labels, "toxic", labelled.fold(5) != 0, bound).select("doc_id", "text", "y").dropDuplicates(["text", "y"]))
    toxic = _counts(rows.where("y = 1"), None, ROWS_LEAST)
    if len(toxic) < 2:
        return ToxicModel()
    clean = _counts(rows.where("y = 0"), frozenset(toxic), 0)
    if "" not in clean:
        return ToxicModel()
    (n_toxic, _), (n_clean, _) = toxic.pop(""), clean.pop("")
    odds = log_odds(Counter({k: v[0] for k, v in toxic.items()}), Counter({k: v[0] for k, v in clean.items()}), n_toxic, n_clean)
    weights = {form: min(o, SCORE_MOST) for form, (o, z) in sorted(odds.items()) if z >= Z_LEAST and o > 1}
    if not weights:
        return ToxicModel()
    sent = docs.sparkSession.sparkContext.broadcast(ToxicModel(weights))

    def token_scores(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, seen = sent.value, Counter()
        for _, texts in text_batches(batches):
            for text in texts:
                for token, c in Counter(TOKENS(text.lower())).items():
                    seen[known.weight(token)] += c
        if seen:
            yield pa.RecordBatch.from_arrays([pa.array(list(seen), pa.float64()), pa.array(list(seen.values()), pa.int64())], ["score", "n"])

    counted = rows.where("y = 0").select("doc_id", "text").mapInArrow(token_scores, "score double, n bigint").groupBy("score").agg(F.sum("n").alias("n")).orderBy("score").toPandas()
    rate = max(moment_root(counted["score"].to_numpy() - PENALTY, (counted["n"] / counted["n"].sum()).to_numpy()), 0.05)

    def best_scores(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = sent.value
        for batch in batches:
            made = [known.scored(t or "") for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array([n for n, _ in made], pa.int64()), pa.array([[s for s, _, _ in found] for _, found in made], pa.list_(pa.float64()))], ["doc_id", "y", "n", "scores"])

    made = sorted(tuple(r) for r in rows.mapInArrow(best_scores, "doc_id bigint, y int, n bigint, scores array<double>").collect())
    spread = sum(y == 0 for _, y, _, _ in made) / sum(max(n, 1) * math.exp(-rate * max(scores, default=0.0)) for _, y, n, scores in made if y == 0)
    beta = logistic(np.array([evidence_of(n, scores, rate, spread) for _, _, n, scores in made]), np.array([y for _, y, _, _ in made]))
    return ToxicModel(weights, rate=rate, spread=spread, bias=float(beta[0]), slopes=(float(beta[1]), float(beta[2])), trained=True)


def score(docs: DataFrame, model: ToxicModel) -> DataFrame:
    """doc_id, score, passages (array of first and last token and expected count in clean text, significant ones only)."""
    spark = docs.sparkSession
    ship(spark)
    sent = spark.sparkContext.broadcast(model)
    kind = pa.list_(pa.struct([("first_token", pa.int32()), ("last_token", pa.int32()), ("expected", pa.float64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = sent.value
        for keys, texts in text_batches(batches):
            passages, scores = [], []
            for text in texts:
                n, found = known.scored(text)
                marked = [{"first_token": a, "last_token": b, "expected": e} for s, a, b in found if (e := known.expected(s, n)) <= SIGNIFICANT]
                passages.append(marked)
                scores.append(known.probability(evidence_of(n, [s for s, _, _ in found], known.rate, known.spread)) if known.trained else 0.0)
            yield pa.RecordBatch.from_arrays([keys, pa.array(scores, pa.float64()), pa.array(passages, kind)], ["doc_id", "score", "passages"])

    chosen = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return chosen.mapInArrow(run, "doc_id bigint, score double, passages array<struct<first_token:int,last_token:int,expected:double>>")


def judge(docs: DataFrame, labels: DataFrame, *, bound: int = TRAINING_ROWS) -> DataFrame:
    """doc_id, held_out, score, predicted, n_passages."""
    scored = score(docs, train(docs, labels, bound=bound))
    return scored.select("doc_id", (labelled.fold(5) == 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), F.size("passages").alias("n_passages"))

"""MinHash fingerprints over word shingles, their bands joined in Spark, Jaccard verified.

A text's shingles are its runs of WORDS lower-cased words (fewer words: the whole sequence; none: no shingle).  Word
hashes combine into shingle hashes by a fixed linear form, and PERMUTATIONS universal hashes a*x + b mod 2**32 keep
their minima, all in vectorised numpy.  near_classes bands the signatures, links equal bands through their smallest
member and verifies links by the exact Jaccard similarity of the shingle sets.

Defined results: null text counts as empty; texts without words have the signature of all ones and equal only each
other; equal texts have equal signatures; very long texts are hashed in blocks; an empty table gives none; other input
columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from momenttree.llm.components import IN_TASK, components
from momenttree.llm.runtime import cut, ship, stored, text_batches

WORDS = 5
PERMUTATIONS = 128
#: Bands of five minima: a pair at a similarity of 0.8 shares none with a probability of 5e-5.
BANDS = 25
#: Members in different classes that one band may compare with one another; in larger bands rare shingles choose the pairs.
PAIRED = 64
SIMILARITY = 0.8
_BLOCK = 2_048
_TOKENS = re.compile(rb"[^\x00-\x20]+").findall
_RANDOM = np.random.default_rng(20_240_501)
MULTIPLIERS = (_RANDOM.integers(0, 1 << 31, PERMUTATIONS, dtype=np.uint32) << np.uint32(1)) | np.uint32(1)
OFFSETS = _RANDOM.integers(0, 1 << 32, PERMUTATIONS, dtype=np.uint32)
#: Odd factors that combine the word hashes of one shingle.
_MIX = _RANDOM.integers(0, 1 << 62, 16, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def shingles(text: str, words: int = WORDS) -> np.ndarray:
    """Distinct-or-not 32-bit shingle hashes of a text."""
    tokens = _TOKENS(text.lower().encode("utf-8", "surrogatepass"))
    if not tokens:
        return np.empty(0, np.uint32)
    hashes = np.fromiter(map(crc32, tokens), np.uint64, len(tokens))
    n = max(len(hashes) - words + 1, 1)
    mixed = np.zeros(n, np.uint64)
    for k in range(min(words, len(hashes))):
        mixed += (hashes[k : k + n] + np.uint64(0x9E3779B9)) * _MIX[k]
    mixed ^= mixed >> np.uint64(29)
    mixed *= np.uint64(0xBF58476D1CE4E5B9)
    return (mixed >> np.uint64(32)).astype(np.uint32)


def signature(hashes: np.ndarray) -> np.ndarray:
    """Minimum of every permutation over the shingle hashes; all ones without any."""
    least = np.full(PERMUTATIONS, 0xFFFFFFFF, np.uint32)
    for at in range(0, len(hashes), _BLOCK):
        block = hashes[at : at + _BLOCK]
        np.minimum(least, (MULTIPLIERS[:, None] * block + OFFSETS[:, None]).min(axis=1), out=least)
    return least


def compact(least: np.ndarray) -> str:
    """Hex of one byte of each minimum."""
    return ((least * np.uint32(0x9E3779B1)) >> np.uint32(24)).astype(np.uint8).tobytes().hex()


def likeness(a: str, b: str) -> float:
    """Jaccard similarity estimated from two compact fingerprints: the share of equal bytes, less what chance makes equal."""
    x, y = np.frombuffer(bytes.fromhex(a), np.uint8), np.frombuffer(bytes.fromhex(b), np.uint8)
    return float(max(0.0, ((x == y).mean() - 1 / 256) / (1 - 1 / 256)))


def fingerprint_of(text: str) -> str:
    return compact(signature(shingles(text)))


def edited(text: str, following: str) -> str:
    """text with its last half (rounded down) replaced by as much of the start of the following text, or all of it."""
    half = len(text) // 2
    return text[: len(text) - half] + following[:half]


def _compare(keys, texts: list[str], following: list[str]) -> pa.RecordBatch:
    prints: dict[str, str] = {}

    def of(text: str) -> str:
        if text not in prints:
            prints[text] = fingerprint_of(text)
        return prints[text]

    rows = []
    for text, after in zip(texts, following, strict=True):
        new = edited(text, after)
        own, other, changed = of(text), of(after), fingerprint_of(new)
        rows.append((len(text), hashlib.sha256(new.encode("utf-8", "surrogatepass")).hexdigest(), own, changed, likeness(own, changed), likeness(own, other)))
    n, sha, own, changed, near, after = zip(*rows, strict=True) if rows else ([],) * 6
    return pa.RecordBatch.from_arrays([keys, pa.array(n, pa.int64()), pa.array(sha, pa.string()), pa.array(own, pa.string()), pa.array(changed, pa.string()), pa.array(near, pa.float64()), pa.array(after, pa.float64())], RESULT.names)


RESULT = pa.schema([("doc_id", pa.int64()), ("n_chars", pa.int64()), ("edited_sha256", pa.string()), ("fingerprint", pa.string()), ("edited_fingerprint", pa.string()), ("near_edited", pa.float64()), ("near_next", pa.float64())])
_DDL = "doc_id bigint, n_chars bigint, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def _sorted_runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Compares each row of a sorted partition with the next; the first text and the last row's text are passed on, whole."""
    edge_kind = [("edge", pa.string()), ("edge_id", pa.int64()), ("edge_text", pa.string())]
    schema = pa.schema([*RESULT, *edge_kind])

    def edges(kind: str, key, text: str) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([*(pa.nulls(1, f.type) for f in RESULT), pa.array([kind]), pa.array([key], pa.int64()), pa.array([text])], schema=schema)

    held = None
    for keys, texts in text_batches(batches):
        if not len(keys):
            continue
        ids = keys.to_pylist()
        if held is None:
            yield edges("first", ids[0], texts[0])
        else:
            ids, texts = [held[0], *ids], [held[1], *texts]
        if len(ids) > 1:
            done = _compare(pa.array(ids[:-1], pa.int64()), texts[:-1], texts[1:])
            yield pa.RecordBatch.from_arrays([*done.columns, *(pa.nulls(done.num_rows, t) for _, t in edge_kind)], schema=schema)
        held = ids[-1], texts[-1]
    if held is not None:
        yield edges("last", *held)


def _pair_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        yield _compare(batch.column(0), [x or "" for x in batch.column(1).to_pylist()], [x or "" for x in batch.column(2).to_pylist()])


def with_edited(docs: DataFrame, partitions: int | None = None) -> DataFrame:
    """For every document its fingerprint, that of its edited text (see edited(); after the last document comes the first), and likenesses.

    Texts are dealt once, by ranges of doc_id, and sorted; a document's successor is the next row of its partition.
    Only the first and the last row of each partition meet their neighbours in a second small stage, so what is
    gathered there counts partitions, not documents.  Rows without a doc_id come first, rows of equal ids in order of their texts.
    """
    spark = docs.sparkSession
    ship(spark)
    chosen = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text"))
    dealt = chosen.repartitionByRange(partitions, "doc_id") if partitions else chosen.repartitionByRange("doc_id")
    done = stored(dealt.sortWithinPartitions("doc_id", "text").select("doc_id", "text").mapInArrow(_sorted_runs, _DDL + ", edge string, edge_id bigint, edge_text string"), "minhash")
    inner = done.where("edge is null").select(RESULT.names)
    ends = done.where("edge is not null")
    # One first and one last row for each non-empty partition: in order of the id, a last row is followed by the next first row.
    heads = sorted(((r.edge_id is not None, r.edge_id) for r in ends.where("edge = 'first'").select("edge_id").collect()), key=lambda x: (x[0], x[1] or 0))
    if not heads:
        return inner
    number = spark.createDataFrame([(key, k, (k - 1) % len(heads)) for k, (_, key) in enumerate(heads)], "head_id bigint, k int, before int")
    tails = sorted(((r.edge_id is not None, r.edge_id) for r in ends.where("edge = 'last'").select("edge_id").collect()), key=lambda x: (x[0], x[1] or 0))
    tail_number = spark.createDataFrame([(key, k) for k, (_, key) in enumerate(tails)], "tail_id bigint, k int")
    firsts = ends.where("edge = 'first'").select("edge_id", F.col("edge_text").alias("after")).join(number, F.col("edge_id").eqNullSafe(F.col("head_id"))).select("after", F.col("before").alias("k"))
    lasts = ends.where("edge = 'last'").select(F.col("edge_id").alias("doc_id"), F.col("edge_text").alias("text")).join(tail_number, F.col("doc_id").eqNullSafe(F.col("tail_id"))).select("doc_id", "text", "k")
    outer = lasts.join(firsts, "k").select("doc_id", "text", "after").mapInArrow(_pair_rows, _DDL)
    return inner.union(outer)


def signatures(docs: DataFrame, *, words: int = WORDS, id_type: str = "bigint") -> DataFrame:
    """doc_id, signature (array of PERMUTATIONS longs), n_shingles."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for keys, texts in text_batches(batches):
            made = [shingles(t, words) for t in texts]
            yield pa.RecordBatch.from_arrays([keys, pa.array([signature(h).astype(np.int64) for h in made], pa.list_(pa.int64())), pa.array([len(h) for h in made], pa.int64())], ["doc_id", "signature", "n_shingles"])

    return docs.select(F.col("doc_id").cast(id_type).alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, f"doc_id {id_type}, signature array<bigint>, n_shingles bigint")


def _bands(signature_col: Column, rows: int, bands: int) -> Column:
    return F.explode(F.array(*(F.struct(F.lit(b).alias("band"), F.xxhash64(F.slice(signature_col, 1 + b * rows, rows)).alias("key")) for b in range(bands))))


def near_classes(docs: DataFrame, *, similarity: float = SIMILARITY, words: int = WORDS, bands: int = BANDS, paired: int = PAIRED) -> DataFrame:
    """doc_id, component_id (smallest doc_id of the class), one row for each row of docs.

    Equal texts first become one vertex, named by a hash of the text.  In each band members are tied to its smallest
    member, and a tie counts if the exact Jaccard similarity of the two shingle sets reaches `similarity`.  That joins a
    group of near copies without its pairs.  Then members of one band that are still in different classes are compared
    with one another, so no link that the bands can show is lost.  In a band with over `paired` such members pairs are
    chosen by rare shingles instead: two sets of a similarity of s share one of the 1 - s rarest of either, so this
    loses none, and a common line that many documents have makes no pairs of all of them.

    Rows with a null doc_id belong to their text's class but never name it (a class of such rows only has a null
    component_id); null and wordless texts are one class; repeated rows give repeated results; an empty table gives none.
    """
    ship(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    name = F.substring(F.sha2(F.col("text").cast("binary"), 256), 1, 32)
    keyed = cut(rows.select("doc_id", name.alias("same")))
    heads = cut(keyed.groupBy("same").agg(F.min("doc_id").alias("head")))
    first = rows.withColumn("same", name).join(heads.toDF("s", "head"), (F.col("same") == F.col("s")) & F.col("doc_id").eqNullSafe(F.col("head")), "left_semi")
    texts = stored(first.dropDuplicates(["same"]).select("same", "text"), "texts")
    made = signatures(texts.select(F.col("same").alias("doc_id"), "text"), words=words, id_type="string")
    banded = stored(made.select(F.col("doc_id").alias("same"), _bands(F.col("signature"), PERMUTATIONS // bands, bands).alias("b")).select("same", "b.band", "b.key"), "banded")

    def jaccard(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values = []
            for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                a, b = set(shingles(x, words).tolist()), set(shingles(y, words).tolist())
                values.append(len(a & b) / len(a | b) if a | b else 1.0)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(values, pa.float64())], ["a", "b", "jaccard"])

    def verified(pairs: DataFrame) -> DataFrame:
        """Links (a, b) among distinct candidate pairs."""
        sides = pairs.join(texts.toDF("a", "text_a"), "a").join(texts.toDF("b", "text_b"), "b").select("a", "b", "text_a", "text_b")
        return cut(sides.mapInArrow(jaccard, "a string, b string, jaccard double").where(F.col("jaccard") >= similarity).select("a", "b"))

    smallest = banded.groupBy("band", "key").agg(F.min("same").alias("a"), F.count("*").alias("n")).where("n > 1").drop("n")
    ties = verified(banded.join(smallest, ["band", "key"]).where("a <> same").select("a", F.col("same").alias("b")).distinct())
    classed = banded.join(components(ties, IN_TASK).select(F.col("id").alias("same"), "component"), "same", "left").select("band", "key", "same", F.coalesce("component", "same").alias("c"))
    mixed = classed.groupBy("band", "key").agg(F.min("c").alias("low"), F.max("c").alias("high"), F.count("*").alias("n")).where("low <> high").select("band", "key", "n")
    open_ = cut(classed.join(mixed, ["band", "key"]))
    few = open_.where(F.col("n") <= paired).drop("n")
    x, y = few.toDF("band", "key", "a", "ca"), few.toDF("band", "key", "b", "cb")
    pairs = x.join(y, ["band", "key"]).where("a < b and ca <> cb").select("a", "b")
    crowd = cut(open_.where(F.col("n") > paired).select("same", "c").distinct())
    if not crowd.isEmpty():
        pairs = pairs.union(_rare_pairs(texts.join(crowd.select("same"), "same", "left_semi"), crowd, similarity, words))
    joined = components(ties.union(verified(pairs.distinct())), IN_TASK)
    named = heads.join(joined.select(F.col("id").alias("same"), "component"), "same", "left").select("same", "head", F.coalesce("component", "same").alias("component"))
    smallest_id = named.groupBy("component").agg(F.min("head").alias("component_id"))
    return keyed.join(named.join(smallest_id, "component").select("same", "component_id"), "same").select("doc_id", "component_id")


def _rare_pairs(texts: DataFrame, classed: DataFrame, similarity: float, words: int) -> DataFrame:
    """Pairs (a, b) of members in different classes that share one of their rarest shingles and whose sizes allow the similarity.

    Of n shingles the n - ceil(s n) + 1 rarest are looked at, in one order for all: sets that miss each other there
    share fewer than s n.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for keys, found in text_batches(batches):
            yield pa.RecordBatch.from_arrays([keys, pa.array([np.unique(shingles(t, words)).astype(np.int64) for t in found], pa.list_(pa.int64()))], ["same", "shingles"])

    sets = texts.select("same", "text").mapInArrow(run, "same string, shingles array<bigint>")
    each = cut(sets.select("same", F.size("shingles").alias("n"), F.explode("shingles").alias("shingle")))
    rarity = each.groupBy("shingle").agg(F.count("*").alias("f")).where("f > 1")
    own = each.join(rarity, "shingle", "left").groupBy("same", "n").agg(F.array_sort(F.collect_list(F.struct(F.coalesce("f", F.lit(1)).alias("f"), "shingle"))).alias("s"))
    prefix = F.slice("s", F.lit(1), (F.col("n") - F.ceil(F.col("n") * similarity - 1e-9) + 1).cast("int"))
    entries = own.select("same", "n", F.explode(prefix).alias("e")).where("e.f > 1").select("same", "n", "e.shingle").join(classed, "same")
    mixed = entries.groupBy("shingle").agg(F.min("c").alias("low"), F.max("c").alias("high")).where("low <> high").select("shingle")
    entries = cut(entries.join(mixed, "shingle", "left_semi"))
    x, y = entries.toDF("shingle", "a", "na", "ca"), entries.toDF("shingle", "b", "nb", "cb")
    fits = (F.least("na", "nb") >= F.greatest("na", "nb") * similarity - 1e-9) & (F.col("a") < F.col("b")) & (F.col("ca") != F.col("cb"))
    return x.join(y, "shingle").where(fits).select("a", "b")

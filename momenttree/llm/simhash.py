"""SimHash near-duplicates by meet-in-the-middle ball hashing.

Fingerprints link at RADIUS = 3 or fewer differing bits, so two that link have a common variant: one flips at most
one bit (65 variants), the other at most two.  Of any three bits two lie in the same 32-bit half, so the second one
needs only the pairs of one half (992 variants).  Every distinct fingerprint emits its variants, they meet in a
shuffle, and colliding pairs are de-duplicated and verified:

* variants within one bit meet as they are: fingerprints that share one differ in at most two bits, so the (at most
  65) members of a variant are linked to the smallest of them, without pairs and without a check;
* variants with two flips in one half all keep the other half as it was.  They travel together as one row of that half
  instead of 496 rows, and meet the halves of the others' variants within one bit.  Which of them agree in the whole is
  the same as a distance of three, which is checked on each colliding pair.

A half met by more than PAIRED fingerprints has more pairs to check than its members have variants (16 checks cost
about one shuffled row); its members emit each variant as a row of its own, and again need no pairs.  No link is lost
either way, and nothing is capped.

Classes are connected components over both kinds of link, computed on distinct fingerprints, so thousands of
exact copies weigh as one row.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from momenttree.llm.components import components
from momenttree.llm.runtime import BATCH_ROWS, cut, ship

RADIUS = 3
#: Fingerprints that meet at one half: up to here pairs are checked, beyond variants are shuffled.
PAIRED = 256
WORDS = re.compile(rb"[^\x20\x09-\x0D]+").findall
UPPER = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")


def fingerprint_of(text: str, words_in_shingle: int = 3) -> int:
    """64-bit SimHash of one text: bit set if set in over half the shingle hashes; no words: zero."""
    words = WORDS(text.encode("utf-8", "surrogatepass").translate(UPPER))
    if not words:
        return 0
    if len(words) < words_in_shingle:
        shingles = [b" ".join(words)]
    else:
        shingles = [b" ".join(x) for x in zip(*(words[k:] for k in range(words_in_shingle)), strict=False)]
    digest = xxhash.xxh64_intdigest
    hashes = np.array([digest(x, 42) for x in shingles], dtype="<u8")
    ones = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 65_536):
        ones += np.unpackbits(hashes[at : at + 65_536].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(hashes), bitorder="little").view("<u8")[0])


def _fingerprint_rows(words_in_shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, BATCH_ROWS):
                batch = whole.slice(at, BATCH_ROWS)
                values = np.array([fingerprint_of(t or "", words_in_shingle) for t in batch.column(1).to_pylist()], dtype=np.uint64).view(np.int64)
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(values), batch.column(2)], ["doc_id", "fp", "text_hash"])

    return run


def fingerprints(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", words_in_shingle: int = 3) -> DataFrame:
    """doc_id, fp (the 64 bits as a signed long), text_hash.  Null and wordless texts have fingerprint zero."""
    ship(docs.sparkSession)
    chosen = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text")).withColumn("text_hash", F.xxhash64("text"))
    return chosen.mapInArrow(_fingerprint_rows(words_in_shingle), "doc_id bigint, fp bigint, text_hash bigint")


def flips(bits: range, width: int) -> list[int]:
    """Masks of at most `width` (0 to 2) set bits out of `bits`, as signed longs."""
    masks = [0]
    if width > 0:
        masks += [1 << b for b in bits]
    if width > 1:
        masks += [1 << a | 1 << b for a in bits for b in bits if a < b]
    return [m - (1 << 64) if m >> 63 else m for m in masks]


def _variants(fp: Column, masks: list[int]) -> Column:
    return F.explode(F.transform(F.array(*map(F.lit, masks)), lambda m: fp.bitwiseXOR(m)))


def _halves(fp: Column) -> Column:
    """Both 32-bit halves of a fingerprint, tagged by which half it is."""
    return F.array(F.struct(F.lit(0).alias("half"), fp.bitwiseAND(F.lit(0xFFFFFFFF)).alias("key")), F.struct(F.lit(1).alias("half"), F.shiftrightunsigned(fp, 32).alias("key")))


def near_links(distinct: DataFrame, paired: int = PAIRED) -> DataFrame:
    """(a, b) links whose components are those of the graph of all pairs of the distinct fingerprints fp within RADIUS."""
    ball = distinct.select("fp", _variants(F.col("fp"), flips(range(64), 1)).alias("variant"))
    shared = ball.select(F.min("fp").over(Window.partitionBy("variant")).alias("a"), F.col("fp").alias("b")).where("a <> b")

    # Three differing bits: one half has at most one of them, so one flip in that half of one fingerprint meets the other's.
    home = distinct.select("fp", F.explode(_halves(F.col("fp"))).alias("h")).select("fp", "h.half", "h.key")
    moved = home.select("fp", "half", _variants(F.col("key"), flips(range(32), 1)).alias("key"))
    crowded = cut(home.groupBy("half", "key").count().where(F.col("count") > paired).select("half", "key"))
    links = [shared]
    if not crowded.isEmpty():
        members = moved.join(crowded, ["half", "key"], "left_semi").select("fp").distinct()
        links.append(_wide_links(members))
        moved = moved.join(crowded, ["half", "key"], "left_anti")
    links.append(home.alias("x").join(moved.alias("y"), _meeting()).select(F.least("x.fp", "y.fp").alias("a"), F.greatest("x.fp", "y.fp").alias("b")))
    return reduce(DataFrame.union, links).distinct()


def _meeting() -> Column:
    return (F.col("x.half") == F.col("y.half")) & (F.col("x.key") == F.col("y.key")) & (F.bit_count(F.col("x.fp").bitwiseXOR(F.col("y.fp"))) == RADIUS)


def _wide_links(members: DataFrame) -> DataFrame:
    """Links of members three bits apart without pairs: at each variant, all with two flips in one half join the smallest within one bit."""
    near = flips(range(64), 1)
    wide = near + [m for half in (range(32), range(32, 64)) for m in flips(half, 2)[33:]]
    masks = F.array(*(F.struct(F.lit(m).alias("mask"), F.lit(k < len(near)).alias("near")) for k, m in enumerate(wide)))
    ball = members.select("fp", F.explode(masks).alias("m")).select("fp", "m.near", F.col("fp").bitwiseXOR(F.col("m.mask")).alias("variant"))
    first = F.min(F.when(F.col("near"), F.col("fp"))).over(Window.partitionBy("variant"))
    return ball.select(first.alias("a"), F.col("fp").alias("b")).where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))


def _classed(docs: DataFrame, words_in_shingle: int, paired: int) -> DataFrame:
    """doc_id, fp, text_hash, class (its smallest fingerprint), component_id."""
    rows = cut(fingerprints(docs, words_in_shingle=words_in_shingle))
    distinct = cut(rows.groupBy("fp").agg(F.min("doc_id").alias("first")))
    joined = components(cut(near_links(distinct.select("fp"), paired))).select(F.col("id").alias("fp"), "component")
    named = cut(distinct.join(joined, "fp", "left").select("fp", "first", F.coalesce("component", "fp").alias("class")))
    smallest = named.groupBy("class").agg(F.min("first").alias("component_id"))
    return rows.join(named.join(smallest, "class").select("fp", "class", "component_id"), "fp")


def classes(docs: DataFrame, *, words_in_shingle: int = 3, paired: int = PAIRED) -> DataFrame:
    """doc_id, fp, component_id (the smallest doc_id of the class) for every row of docs.

    Rows with a null doc_id belong to their fingerprint's class but never name it (a class of such rows only has a null
    component_id); repeated rows give repeated results; equal texts always share a class; an empty table gives none.
    """
    return _classed(docs, words_in_shingle, paired).select("doc_id", "fp", "component_id")


def as_hex(fp: Column) -> Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


def keep_one(docs: DataFrame) -> DataFrame:
    """One row of docs for each class: of those with its smallest doc_id the one with the smallest text hash.

    Of rows equal in id and text the one smallest in all columns stays, so the columns have to be orderable.  Rows
    without a doc_id stay.
    """
    named = _classed(docs, 3, PAIRED).where("doc_id = component_id").groupBy("class").agg(F.min(F.struct("doc_id", "text_hash")).alias("k"))
    chosen = cut(named.select("k.*").distinct())
    mark = "__text_hash"
    marked = docs.where("doc_id is not null").withColumn(mark, F.xxhash64(F.col("text").cast("string")))
    kept = marked.join(chosen.toDF("__id", "__hash"), (F.col("doc_id") == F.col("__id")) & (F.col(mark) == F.col("__hash")), "left_semi")
    whole = F.struct(*(F.col(f"`{c}`") for c in docs.columns))
    single = kept.groupBy("doc_id", mark).agg(F.min(whole).alias("w")).select("w.*")
    return single.select(docs.columns).union(docs.where("doc_id is null"))

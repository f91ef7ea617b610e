"""From texts to bags: words, vocabulary, one sparse row for each document."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from momenttree.functions import text as T
from momenttree.runtime import ship, stored

BAG = "doc_id bigint, len double, terms array<int>, counts array<double>"


def tokens(docs: DataFrame, *, stop: list[str] | None = None, stems: bool = False, text_col: str = "text") -> DataFrame:
    """doc_id, words (array).  Rows stay; a null text has no words."""
    found = T.words(F.col(text_col))
    if stop:
        found = T.without(found, stop)
    if stems:
        found = F.transform(found, T.stem)
    return docs.select("doc_id", found.alias("words"))


def long_counts(tokenised: DataFrame) -> DataFrame:
    """doc_id, term, c: occurrences."""
    return tokenised.select("doc_id", F.explode("words").alias("term")).groupBy("doc_id", "term").agg(F.count("*").alias("c"))


#: Up to so many rows are numbered by one window in one task; more are sorted and numbered in ranges.
NUMBERED_AT_ONCE = 100_000


def numbered(rows: DataFrame, order: list[Column], name: str) -> DataFrame:
    """rows with their place in a total order, from 0, without a task that sees them all.

    Sorted once by ranges and stored; each range is numbered on its own, and the sizes of the ranges before it, a table
    of one row a range, are added.
    """
    ranges = stored(rows.orderBy(*order).withColumn("_range", F.spark_partition_id()), "numbered")
    sizes = ranges.groupBy("_range").agg(F.count("*").alias("_n"))
    before = sizes.select("_range", (F.sum("_n").over(Window.orderBy("_range")) - F.col("_n")).alias("_before"))
    within = F.row_number().over(Window.partitionBy("_range").orderBy(*order)) - 1
    return ranges.withColumn("_at", within).join(F.broadcast(before), "_range").withColumn(name, (F.col("_before") + F.col("_at")).cast("int")).drop("_range", "_before", "_at")


def frequency_ranks(rows: DataFrame, tie: str, buckets: int = 10) -> DataFrame:
    """tie, rank, dense_rank, percent_rank, cume_dist and ntile of rows (tie, tf) by descending tf; ntile breaks ties by `tie`, which is unique.

    The window functions of the same names over all rows, without a task that sees them all: rows of one tf share every rank but
    ntile, so these are made on the table of frequencies (with n occurrences, less than sqrt(2 n) rows), and ntile by the row's place.
    """
    w = Window.orderBy(F.col("tf").desc())
    sizes = rows.groupBy("tf").agg(F.count("*").alias("_n")).withColumn("_upto", F.sum("_n").over(w)).withColumn("dense_rank", F.dense_rank().over(w))
    sizes = sizes.withColumn("_total", F.sum("_n").over(Window.partitionBy())).withColumn("rank", (F.col("_upto") - F.col("_n") + 1).cast("int"))
    percent = F.when(F.col("_total") > 1, (F.col("rank") - 1) / F.greatest(F.col("_total") - 1, F.lit(1))).otherwise(0.0)
    sizes = sizes.select("tf", "rank", "dense_rank", percent.alias("percent_rank"), (F.col("_upto") / F.col("_total")).alias("cume_dist"), "_total")
    placed = numbered(rows.select(tie, "tf"), [F.col("tf").desc(), F.col(tie)], "_place").join(F.broadcast(sizes), "tf")
    small = F.floor(F.col("_total") / buckets)  # rows of a bucket; the first `larger` buckets have one more
    larger = F.col("_total") % buckets
    first = larger * (small + 1)
    ntile = F.when(F.col("_place") < first, F.floor(F.col("_place") / (small + 1))).otherwise(larger + F.floor((F.col("_place") - first) / F.greatest(small, F.lit(1))))
    return placed.select(tie, "rank", "dense_rank", "percent_rank", "cume_dist", (ntile + 1).cast("int").alias("ntile"))


def count_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(term, rows that hold it, occurrences) of each batch."""
    for batch in batches:
        words = batch.column(0)
        owner = np.repeat(np.arange(batch.num_rows), np.diff(words.offsets.to_numpy()))
        found = pc.dictionary_encode(words.flatten())
        code, v = found.indices.to_numpy(zero_copy_only=False).astype(np.int64), len(found.dictionary)
        if v:
            rows = np.unique(owner * v + code) % v
            yield pa.RecordBatch.from_arrays([found.dictionary, pa.array(np.bincount(rows, minlength=v)), pa.array(np.bincount(code, minlength=v))], ["term", "df", "tf"])


def vocabulary(tokenised: DataFrame, *, min_df: int = 1, max_df: int | None = None, top: int | None = None) -> DataFrame:
    """term, term_id, df, tf: ids run from 0 by descending document frequency, then by term, so they do not depend on partitions.

    Each row is a document, so occurrences and documents are counted in place, a batch at a time in Arrow and numpy, and one
    aggregation adds the batches up: no word occurrence becomes a row.  A bounded vocabulary (top of at most NUMBERED_AT_ONCE) is a
    distributed top-n and numbered by a window over those rows; an unbounded one is numbered in sorted ranges.
    """
    ship(tokenised.sparkSession)
    parts = tokenised.select(F.coalesce("words", F.array().cast("array<string>")).alias("words")).mapInArrow(count_batches, "term string, df bigint, tf bigint")
    counted = parts.groupBy("term").agg(F.sum("df").alias("df"), F.sum("tf").alias("tf")).where(F.col("df") >= min_df)
    if max_df is not None:
        counted = counted.where(F.col("df") <= max_df)
    order = [F.col("df").desc(), F.col("term")]
    if top is not None:
        counted = counted.orderBy(*order).limit(top)
    if top is not None and top <= NUMBERED_AT_ONCE:
        counted = counted.withColumn("term_id", F.row_number().over(Window.orderBy(*order)) - 1)
    else:
        counted = numbered(counted, order, "term_id")
    return counted.select("term", "term_id", "df", "tf")


#: A vocabulary of at most so many terms is sent to the workers (about 20 bytes each); a larger one is joined by shuffle.
VOCABULARY_BROADCAST = 1_000_000


def bags(tokenised: DataFrame, vocab: DataFrame, *, min_len: float = 3, size: int | None = None) -> DataFrame:
    """doc_id, len, terms, counts: one row for each row of at least min_len known words, terms ascending.

    With a vocabulary whose checked size allows sending it, every row is counted where it is, in vectorised Arrow and
    numpy steps, without any shuffle.  Otherwise words are joined to ids and gathered by row.  Both give the same bags.
    """
    if (vocab.count() if size is None else size) > VOCABULARY_BROADCAST:
        return _shuffled_bags(tokenised, vocab, min_len)
    spark = tokenised.sparkSession
    ship(spark)
    terms = [r.term for r in vocab.select("term", "term_id").orderBy("term_id").collect()]
    sent = spark.sparkContext.broadcast(terms)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = pa.array(sent.value, pa.string())
        v = max(len(known), 1)
        for batch in batches:
            words = batch.column(1)
            sizes = np.diff(words.offsets.to_numpy())
            owner = np.repeat(np.arange(batch.num_rows), sizes)
            found = pc.index_in(words.flatten(), value_set=known).to_numpy(zero_copy_only=False)
            there = ~np.isnan(found) if found.dtype.kind == "f" else np.ones(len(found), bool)
            key, count = np.unique(owner[there].astype(np.int64) * v + found[there].astype(np.int64), return_counts=True)
            row = key // v
            length = np.bincount(row, count, batch.num_rows)
            kept = length >= min_len
            at = kept[row]
            offsets = np.concatenate([[0], np.cumsum(np.bincount(row[at], minlength=batch.num_rows)[kept])]).astype(np.int32)
            lists = [pa.ListArray.from_arrays(pa.array(offsets), pa.array(x)) for x in ((key[at] % v).astype(np.int32), count[at].astype(np.float64))]
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(pa.array(kept)), pa.array(length[kept]), *lists], ["doc_id", "len", "terms", "counts"])

    return tokenised.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.coalesce("words", F.array().cast("array<string>")).alias("words")).mapInArrow(run, BAG)


def _shuffled_bags(tokenised: DataFrame, vocab: DataFrame, min_len: float) -> DataFrame:
    """Rows are told apart by a key of their own, so rows of one doc_id stay different bags here too."""
    keyed = tokenised.select(F.monotonically_increasing_id().alias("row"), F.col("doc_id").cast("bigint").alias("doc_id"), "words")
    words = keyed.select("row", "doc_id", F.explode("words").alias("term")).join(vocab.select("term", "term_id"), "term")
    counted = words.groupBy("row", "doc_id", "term_id").agg(F.count("*").cast("double").alias("c"))
    pairs = F.array_sort(F.collect_list(F.struct("term_id", "c")))
    made = counted.groupBy("row", "doc_id").agg(F.sum("c").alias("len"), pairs.alias("pairs"))
    return made.where(F.col("len") >= min_len).select("doc_id", "len", F.col("pairs.term_id").alias("terms"), F.col("pairs.c").alias("counts"))


def long_of(bag_rows: DataFrame) -> DataFrame:
    """doc_id, term_id, c of bags."""
    return bag_rows.select("doc_id", F.explode(F.arrays_zip("terms", "counts")).alias("t")).select("doc_id", F.col("t.terms").alias("term_id"), F.col("t.counts").cast("bigint").alias("c"))


def long_bags(tokenised: DataFrame, vocab: DataFrame, size: int | None = None) -> DataFrame:
    """doc_id, term_id, c for words of the vocabulary, of rows of any length."""
    return long_of(bags(tokenised, vocab, min_len=1, size=size))


def dedupe(docs: DataFrame) -> DataFrame:
    """One row, the smallest doc_id, of each text."""
    keep = docs.groupBy(F.sha2(F.col("text").cast("binary"), 256).alias("h")).agg(F.min("doc_id").alias("doc_id")).select("doc_id")
    return docs.join(keep, "doc_id", "left_semi")


def cap_tokens(tokenised: DataFrame, most: int, seed: int = 0) -> DataFrame:
    """A sample without replacement of at most `most` tokens of each document.

    Averages over pairs and triples of distinct tokens keep their expectation, so second and third moments do.
    """
    keyed = F.transform("words", lambda w, i: F.struct(F.xxhash64(F.lit(seed), "doc_id", i).alias("h"), i.alias("i"), w.alias("w")))
    chosen = F.array_sort(F.transform(F.slice(F.array_sort(keyed), 1, most), lambda x: F.struct(x["i"], x["w"])))
    return tokenised.withColumn("words", F.when(F.size("words") > most, F.transform(chosen, lambda x: x["w"])).otherwise(F.col("words")))


def sentence_rows(docs: DataFrame) -> DataFrame:
    """doc_id, sent_no, words of every sentence that has words."""
    split = docs.select("doc_id", F.posexplode(T.sentences(F.col("text"))).alias("sent_no", "sentence"))
    return split.select("doc_id", "sent_no", T.words(F.col("sentence")).alias("words")).where(F.size("words") > 0)

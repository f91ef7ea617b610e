"""Frequent phrases, their quality, their counts by topic, their rank."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from momenttree.functions import paths
from momenttree.functions import text as T
from momenttree.operators.corpus import count_batches
from momenttree.runtime import cut, ship, stored

#: A phrase table of at most so many rows is broadcast; a larger one is joined by shuffle.
PHRASES_BROADCAST = 1_000_000
#: Phrases that are sent as arrays (8 bytes each), beyond which rows are joined, and shares of phrases in nodes that are sent
#: at once (18 bytes each); more take further scans, in groups of nodes, up to SCANS of them.
PHRASES_SENT, SHARES_SENT, SCANS = 5_000_000, 4_000_000, 16
#: Words that a worker looks up at once.
_WORDS_AT_ONCE = 200_000


def grams(sentences: DataFrame, n: int) -> DataFrame:
    """doc_id, sent_no, pos, phrase: contiguous runs of n words, words joined by a space."""
    return sentences.where(F.size("words") >= n).select("doc_id", "sent_no", F.posexplode(_runs(n)).alias("pos", "phrase"))


def _runs(n: int) -> Column:
    return F.transform(F.sequence(F.lit(1), F.size("words") - n + 1), lambda i: F.array_join(F.slice("words", i, n), " "))


#: Phrases up to this length are counted from the sentences, a length at a time; longer ones from stretches of frequent ones.
RESCANNED = 4


def mine_phrases(sentences: DataFrame, min_support: int, max_len: int | None = None) -> DataFrame:
    """phrase, n, support of every contiguous pattern that occurs min_support times.

    A run of n words is a candidate only if both of its runs of n - 1 words are frequent: each of the first lengths
    rescans the sentences with two semi-joins and one aggregation with partial sums.  A frequent run of more than n words
    lies within a stretch whose runs of n words are all frequent, so from there on only the distinct stretches are kept,
    with the number of their places.  All runs of up to twice the length are counted in them at once, then they are cut
    anew by the longest, and so on until nothing is left: rounds grow with the logarithm of the longest phrase.
    """
    out, here, n = None, grams(sentences, 1), 1
    while True:
        counted = cut(here.groupBy("phrase").agg(F.count("*").alias("support")).where(F.col("support") >= min_support).select("phrase", F.lit(n).alias("n"), "support"))
        found = counted.count()
        if not found:
            break
        out = counted if out is None else out.union(counted)
        last = counted.select("phrase")
        if n == max_len or n == RESCANNED:
            break
        n += 1
        known = F.broadcast(last) if found <= PHRASES_BROADCAST else last
        runs = grams(sentences, n).select("phrase", F.regexp_replace("phrase", " [^ ]*$", "").alias("head"), F.regexp_replace("phrase", "^[^ ]* ", "").alias("tail"))
        here = runs.join(known.toDF("head"), "head", "left_semi").join(known.toDF("tail"), "tail", "left_semi").select("phrase")
    if out is None:
        return here.limit(0).select("phrase", F.lit(1).alias("n"), F.lit(0).cast("bigint").alias("support"))
    rows = sentences.select("words", F.lit(1).cast("bigint").alias("places"))
    while found and n != max_len:
        rows = cut(_stretches(rows, F.broadcast(last) if found * n <= 4 * PHRASES_BROADCAST else last, n))
        most = 2 * n if max_len is None else min(2 * n, max_len)
        runs = F.flatten(F.transform(F.sequence(F.lit(n + 1), F.least(F.lit(most), F.size("words"))), lambda k: F.transform(F.sequence(F.lit(1), F.size("words") - k + 1), lambda i: F.struct(k.alias("n"), F.array_join(F.slice("words", i, k), " ").alias("phrase")))))
        each = rows.select("places", F.explode(runs).alias("r")).groupBy("r.phrase", "r.n").agg(F.sum("places").alias("support"))
        counted = cut(each.where(F.col("support") >= min_support).select("phrase", "n", "support"))
        out, n = out.union(counted), most
        last = counted.where(F.col("n") == n).select("phrase")
        found = last.count()
    return out


def _stretches(rows: DataFrame, known: DataFrame, n: int) -> DataFrame:
    """words, places: the distinct longest stretches of more than n words of rows in which every run of n words is known."""
    kept = rows.where(F.size("words") > n).select(F.monotonically_increasing_id().alias("row"), "places", "words").select("row", "places", F.posexplode(_runs(n)).alias("pos", "phrase")).join(known, "phrase", "left_semi")
    block = F.col("pos") - F.row_number().over(Window.partitionBy("row").orderBy("pos"))
    runs = kept.withColumn("block", block).groupBy("row", "places", "block").agg(F.array_sort(F.collect_list(F.struct("pos", "phrase"))).alias("s")).where(F.size("s") > 1)
    words = F.concat(F.split(F.col("s")[0]["phrase"], " "), F.transform(F.slice("s", F.lit(2), F.size("s") - 1), lambda x: F.substring_index(x["phrase"], " ", -1)))
    return runs.select(words.alias("words"), "places").groupBy("words").agg(F.sum("places").alias("places"))


def longest(phrases: DataFrame) -> int:
    """Words of the longest phrase, 1 without any."""
    return phrases.agg(F.max("n")).first()[0] or 1


def complete_ratio(phrases: DataFrame) -> DataFrame:
    """phrase, n, support, ratio: the largest support among phrases one word longer that begin or end with it, over its own."""
    longer = phrases.where("n > 1").select(F.col("n").alias("m"), F.col("support").alias("s"), F.explode(F.array(F.regexp_replace("phrase", " [^ ]*$", ""), F.regexp_replace("phrase", "^[^ ]* ", ""))).alias("phrase"))
    most = longer.groupBy("phrase").agg(F.max("s").alias("s"))
    return phrases.join(most, "phrase", "left").select("phrase", "n", "support", (F.coalesce("s", F.lit(0)) / F.col("support")).alias("ratio"))


def complete(phrases: DataFrame, gamma: float = 0.9) -> DataFrame:
    """Phrases that no longer one nearly always extends."""
    return complete_ratio(phrases).where(F.col("ratio") < gamma).select("phrase", "n", "support")


def phraseness(phrases: DataFrame, n_tokens: float) -> DataFrame:
    """phrase, n, support, z for n > 1: the least significance over all ways to split the phrase in two independent parts.

    Parts are looked up by hash, which is exact where phrases hold the parts of every phrase, as mined ones do, and no
    two of them share a hash; otherwise by their words.
    """
    words = F.split("phrase", " ")
    splits = phrases.where("n > 1").select("phrase", "n", "support", F.explode(F.expr("sequence(1, n - 1)")).alias("at"))
    left, right = F.array_join(F.slice(words, F.lit(1), F.col("at")), " "), F.array_join(F.slice(words, F.col("at") + 1, F.col("n") - F.col("at")), " ")
    total, hashes = phrases.agg(F.count("*"), F.count_distinct(F.xxhash64("phrase"))).first()
    key = F.xxhash64 if total == hashes else lambda x: x
    known = phrases.select(key(F.col("phrase")).alias("key"), F.col("support").alias("f"))
    known = F.broadcast(known) if total <= PHRASES_BROADCAST else known
    joined = splits.select("phrase", "n", "support", key(left).alias("left"), key(right).alias("right")).join(known.toDF("left", "fl"), "left").join(known.toDF("right", "fr"), "right")
    expected = F.col("fl") * F.col("fr") / F.lit(float(n_tokens))
    return joined.groupBy("phrase", "n", "support").agg(F.min((F.col("support") - expected) / F.sqrt("support")).alias("z"))


#: Own choice, since the method leaves the test open: standard deviations above what independent parts would give.
SIGNIFICANT = 3.0


def quality(phrases: DataFrame, n_tokens: float, gamma: float = 0.9, least: float = SIGNIFICANT) -> DataFrame:
    """phrase, n, support of the complete phrases; those of several words also have a phraseness of at least least."""
    chance = phraseness(phrases, n_tokens).where(F.col("z") < least).select("phrase")
    return complete(phrases, gamma).join(chance, "phrase", "left_anti").select("phrase", "n", "support")


def good_of(mined: Mined, gamma: float = 0.9, least: float = SIGNIFICANT) -> DataFrame:
    """As quality, of what has been mined; with their ids where they have some."""
    if mined.codes is None:
        return quality(mined.phrases, n_tokens_of(mined.by_doc), gamma, least)
    return mined.where((F.col("ratio") < gamma) & ((F.col("n") == 1) | (F.col("z") >= least))).select("phrase", "n", "support", "id")


def phrase_counts(sentences: DataFrame, phrases: DataFrame, max_len: int) -> DataFrame:
    """doc_id, phrase, c: all occurrences, overlapping ones too.  phrases is sent to all tasks if its checked size allows."""
    known = phrases.select("phrase")
    if known.limit(PHRASES_BROADCAST + 1).count() <= PHRASES_BROADCAST:
        known = F.broadcast(known)
    runs = [F.when(F.size("words") >= n, _runs(n)).otherwise(F.array().cast("array<string>")) for n in range(1, max_len + 1)]
    return sentences.select("doc_id", F.explode(F.concat(*runs)).alias("phrase")).join(known, "phrase", "left_semi").groupBy("doc_id", "phrase").agg(F.count("*").alias("c"))


def by_document(docs: DataFrame, tag: Column | None = None) -> DataFrame:
    """doc_id, sents (array of arrays of words): one stored row for each doc_id, whose rows, if several, are put together.

    With tag (a string), also tags: that of each of these rows, nulls left out.
    """
    sents = F.filter(F.transform(T.sentences(F.col("text")), T.words), lambda w: F.size(w) > 0)
    made = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), sents.alias("sents"), *([] if tag is None else [F.array_compact(F.array(tag)).alias("tags")]))
    if not docs.groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1").isEmpty():
        made = made.groupBy("doc_id").agg(*(F.flatten(F.collect_list(c)).alias(c) for c in made.columns[1:]))
    return stored(made, "sentences")


def sentences_of(by_doc: DataFrame) -> DataFrame:
    """doc_id, sent_no, words, as corpus.sentence_rows, but for the numbers of sentences without words."""
    return by_doc.select("doc_id", F.posexplode("sents").alias("sent_no", "words"))


class Mined:
    """Frequent phrases (phrases: phrase, n, support, id, ratio, z as complete_ratio and phraseness give them), and codes (doc_id, codes, tags as by_document has them): the words' ids, -1 for other words and after sentences.

    A phrase of m + d words, m a power of two and d of at most m, is known by the ids of its first and its last m words.
    tables holds for each m and d the sorted pairs and the first phrase's id, so workers look codes up by numbers alone.
    measures has no texts: workers write them from the pairs where they are wanted (spelling), so no step holds or sends
    the words of all phrases.
    """

    def __init__(self, by_doc: DataFrame, phrases: DataFrame | None = None, codes: DataFrame | None = None, tables: list | None = None, size: int = 0, measures: DataFrame | None = None, spelling=None):
        self.by_doc, self.codes, self.size, self.measures, self.spelling = by_doc, codes, size, measures, spelling
        self.sent = by_doc.sparkSession.sparkContext.broadcast(tables) if codes is not None else None
        self.phrases = self._named(measures) if phrases is None else phrases

    def where(self, condition: Column | str) -> DataFrame:
        """phrases under a condition on n, support, ratio and z; only these are written out."""
        return self.phrases.where(condition) if self.codes is None else self._named(self.measures.where(condition))

    def _named(self, measures: DataFrame) -> DataFrame:
        sent, spelling = self.sent, self.spelling

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                ids = batch.column(0).to_numpy()
                for first, last in _pieces(_lengths(ids, sent.value)):
                    part = batch.slice(first, last - first)
                    yield pa.RecordBatch.from_arrays([_spelled(ids[first:last], sent.value, spelling.value), *part.columns[1:3], part.column(0), *part.columns[3:]], ["phrase", "n", "support", "id", "ratio", "z"])

        return measures.mapInArrow(run, "phrase string, n int, support bigint, id int, ratio double, z double")


def _starts(tables: list) -> np.ndarray:
    """The first phrase's id of each number of words from 2 on."""
    return np.array([start for by_step in tables for _, start in by_step], np.int64)


def _lengths(ids: np.ndarray, tables: list) -> np.ndarray:
    """Words of each phrase."""
    return np.searchsorted(_starts(tables), ids, "right") + 1


def _pieces(sizes: np.ndarray) -> list[tuple[int, int]]:
    """first, last + 1 of groups in order, each of about _WORDS_AT_ONCE words."""
    group = np.cumsum(sizes) // _WORDS_AT_ONCE
    cuts = np.flatnonzero(group[1:] != group[:-1]) + 1
    return [(int(a), int(b)) for a, b in zip([0, *cuts], [*cuts, len(sizes)], strict=True) if b > a]


def _matrix(ids: np.ndarray, n: int, tables: list, powers: list[tuple[int, np.ndarray]]) -> np.ndarray:
    """The words' ids of phrases of n words.  powers: first id and words of all phrases of 1, 2, 4, ... words."""
    if n == 1:
        return powers[0][1][ids]
    k = (n - 1).bit_length() - 1
    m, (base, shorter) = 1 << k, powers[k]
    keys, start = tables[k][n - m - 1]
    key = keys[ids - start]
    return np.hstack([shorter[(key >> 31) - base], shorter[(key & ((1 << 31) - 1)) - base][:, 2 * m - n :]])


def _spelled(ids: np.ndarray, tables: list, spelling: tuple[list[str], list]) -> pa.Array:
    """The texts of phrases."""
    words, powers = spelling
    lengths = _lengths(ids, tables)
    ends = np.cumsum(lengths)
    codes = np.empty(int(ends[-1]) if len(ends) else 0, np.int32)
    for n in np.unique(lengths):
        own = np.flatnonzero(lengths == n)
        codes[(ends[own] - n)[:, None] + np.arange(n)] = _matrix(ids[own], int(n), tables, powers)
    lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], ends]), pa.int32()), pa.array(words, pa.string()).take(pa.array(codes)))
    return pc.binary_join(lists, " ")


def _lookup(table: tuple[np.ndarray, int], key: np.ndarray) -> np.ndarray:
    """ids of keys, -1 for others."""
    keys, start = table
    if not len(keys):
        return np.full(len(key), -1, np.int64)
    place = np.minimum(np.searchsorted(keys, key), len(keys) - 1)
    return np.where(keys[place] == key, place + start, -1)


def _doubled(codes: np.ndarray, tables: list) -> np.ndarray:
    """The id at each place of the run of 2 ** len(tables) words that begins there, or -1."""
    at = codes.astype(np.int64)
    for k, by_step in enumerate(tables):
        m = 1 << k
        own = np.flatnonzero((at[:-m] >= 0) & (at[m:] >= 0)) if len(at) > m else np.empty(0, np.int64)
        longer = np.full(len(at), -1, np.int64)
        if len(own):
            longer[own] = _lookup(by_step[m - 1], (at[own] << 31) | at[own + m])
        at = longer
    return at


def _chunks(batch: pa.RecordBatch, column: int) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """first row, last row + 1, codes and their rows (from 0), a group of rows at a time."""
    lists = batch.column(column)
    starts = np.concatenate([[0], np.cumsum(pc.list_value_length(lists).to_numpy(zero_copy_only=False))]).astype(np.int64)
    codes, first = lists.flatten().to_numpy(zero_copy_only=False), 0
    while first < batch.num_rows:
        last = max(first + 1, int(np.searchsorted(starts, starts[first] + _WORDS_AT_ONCE, "right")) - 1)
        yield first, last, codes[starts[first] : starts[last]], np.repeat(np.arange(last - first), np.diff(starts[first : last + 1]))
        first = last


def _summed(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.argsort(keys, kind="stable")
    keys = keys[order]
    begins = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else np.empty(0, np.int64)
    return keys[begins], np.add.reduceat(counts[order], begins) if len(keys) else counts


def _packed(x: np.ndarray) -> bytes:
    """Numbers of 8 bytes, compressed a byte place at a time."""
    return pa.compress(np.ascontiguousarray(x.view(np.uint8).reshape(-1, 8).T).tobytes(), codec="zstd", asbytes=True)


def _unpacked(data: bytes, size: int, kind: type = np.int64) -> np.ndarray:
    planes = np.frombuffer(pa.decompress(data, size * 8, codec="zstd", asbytes=True), np.uint8).reshape(8, size)
    return np.ascontiguousarray(planes.T).view(kind).ravel()


def _partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def _for_sums(codes: DataFrame) -> DataFrame:
    """codes in at most two tasks a core: each task puts out sums over all it has read, so these follow the cores, not the input."""
    return codes.coalesce(2 * codes.sparkSession.sparkContext.defaultParallelism)


def mine(by_doc: DataFrame, min_support: int, max_len: int | None = None) -> Mined:
    """The phrases that mine_phrases finds, by numbers: each round doubles the length.

    Words become ids once.  In a round at m words all runs of m + 1 to 2 m words whose first and last m words are frequent
    are counted as pairs of ids; from four words on only the distinct stretches whose runs of four words are all frequent
    are looked at, with the number of their places.  Where the phrases are too many to send, mine_phrases does it by rows.
    """
    spark = by_doc.sparkSession
    ship(spark)
    by_rows = lambda: Mined(by_doc, mine_phrases(sentences_of(by_doc), min_support, max_len))
    parts = by_doc.select(F.flatten("sents").alias("words")).mapInArrow(count_batches, "term string, df bigint, tf bigint")
    singles = cut(parts.groupBy("term").agg(F.sum("tf").alias("tf")).where(F.col("tf") >= min_support))
    if singles.count() > PHRASES_BROADCAST:
        return by_rows()
    table = singles.toArrow().sort_by("term")
    terms, supports, total = table.column("term").combine_chunks(), [table.column("tf").to_numpy()], table.num_rows
    words, powers = terms.to_pylist(), [(0, np.arange(total, dtype=np.int32)[:, None])]
    codes = stored(by_doc.mapInArrow(_encoder(spark.sparkContext.broadcast(words)), "doc_id bigint, codes array<int>" + ", tags array<string>" * ("tags" in by_doc.columns)), "codes")
    rows, tables = codes.select("codes", F.lit(1).cast("bigint").alias("places")), []
    while len(powers[-1][1]) and (most := (1 << len(tables)) if max_len is None else min(1 << len(tables), max_len - (1 << len(tables)))) > 0:
        m = 1 << len(tables)
        if m == 4:
            found = rows.mapInArrow(_stretcher(spark.sparkContext.broadcast(tables)), "codes array<int>")
            rows = stored(found.groupBy("codes").agg(F.count("*").alias("places")), "stretches")
        parts = _partitions(spark)
        pairs = rows.mapInArrow(_pairer(spark.sparkContext.broadcast(tables), most, parts), "part int, d int, size int, keys binary, counts binary")
        counted = cut(pairs.repartitionById(parts, F.col("part")).mapInArrow(_merger(min_support), "d int, h int, t int, c bigint"))
        if total + counted.count() > PHRASES_SENT:
            return by_rows()
        table = counted.toArrow()
        d, h, t, c = (table.column(x).to_numpy() for x in ("d", "h", "t", "c"))
        by_step = []
        for step in range(1, m + 1):
            own = np.flatnonzero(d == step)
            key = (h[own].astype(np.int64) << 31) | t[own]
            own, key = own[order := np.argsort(key)], key[order]
            by_step.append((key, total))
            total += len(own)
            supports.append(c[own])
        tables.append(by_step)
        start = by_step[-1][1]
        powers.append((start, _matrix(np.arange(start, total), 2 * m, tables, powers)))
    support = np.concatenate(supports)
    ratio, z = _measures(tables, powers, support.astype(np.float64), n_tokens_of(by_doc))
    ids = np.arange(total, dtype=np.int32)
    made = pa.table({"id": ids, "n": _lengths(ids, tables).astype(np.int32), "support": support, "ratio": ratio, "z": z})
    return Mined(by_doc, None, codes, tables, total, cut(spark.createDataFrame(made)), spark.sparkContext.broadcast((words, powers)))


def _measures(tables: list, powers: list, support: np.ndarray, n_tokens: int) -> tuple[np.ndarray, np.ndarray]:
    """ratio and z of all phrases from the ids of their words, a length at a time: head and tail lead to every part.

    Of m + 1 words, the pair of ids is head and tail; others are looked up by their words.
    """
    head, tail, most, z = (np.zeros(len(support), x) for x in (np.int32, np.int32, float, float))
    starts = [0, *_starts(tables).tolist(), len(support)]
    for n in range(2, len(starts)):
        own = np.arange(starts[n - 1], starts[n])
        if not len(own):
            break
        k = (n - 1).bit_length() - 1
        if n == (1 << k) + 1:
            key = tables[k][0][0]
            head[own], tail[own] = key >> 31, key & ((1 << 31) - 1)
        else:
            known = {row.tobytes(): i for i, row in enumerate(_matrix(np.arange(starts[n - 2], starts[n - 1]), n - 1, tables, powers), starts[n - 2])}
            x = _matrix(own, n, tables, powers)
            for side, part in ((head, x[:, :-1]), (tail, x[:, 1:])):
                side[own] = [known[row.tobytes()] for row in part]
        for side in (head, tail):
            np.maximum.at(most, side[own], support[own])
        rights, left, worst = [own], own, np.zeros(len(own))
        for _ in range(n - 1):
            rights.append(tail[rights[-1]])
        for k in range(1, n):
            left = head[left]
            np.maximum(worst, support[left] * support[rights[n - k]], out=worst)
        z[own] = (support[own] - worst / n_tokens) / np.sqrt(support[own])
    return most / support, z


def _encoder(sent):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = pa.array(sent.value, pa.string())
        for batch in batches:
            sents = batch.column(1)
            ends = np.concatenate([[0], np.cumsum(pc.fill_null(pc.list_value_length(sents), 0).to_numpy(zero_copy_only=False))]).astype(np.int64)
            inner = sents.flatten()
            lengths = pc.list_value_length(inner).to_numpy(zero_copy_only=False).astype(np.int64)
            found = pc.fill_null(pc.index_in(inner.flatten(), value_set=known), -1).to_numpy(zero_copy_only=False)
            codes = np.full(len(found) + len(lengths), -1, np.int32)
            codes[np.arange(len(found)) + np.repeat(np.arange(len(lengths)), lengths)] = found
            offsets = np.concatenate([[0], np.cumsum(lengths + 1)])[ends]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(codes)), *batch.columns[2:]], ["doc_id", "codes", *batch.schema.names[2:]])

    return run


def _stretcher(sent):
    """codes, one row for each longest stretch of more than m words whose runs of m words are all frequent, closed by -1."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = sent.value
        m = 1 << len(tables)
        for batch in batches:
            for _, _, codes, _ in _chunks(batch, 0):
                there = np.concatenate([[False], _doubled(codes, tables) >= 0, [False]])
                begins, ends = np.flatnonzero(there[1:] & ~there[:-1]), np.flatnonzero(~there[1:] & there[:-1])
                begins, ends = (x[ends - begins > 1] for x in (begins, ends))
                sizes = ends - begins + m  # the words and one -1
                offsets = np.concatenate([[0], np.cumsum(sizes)])
                out = codes[np.repeat(begins - offsets[:-1], sizes) + np.arange(offsets[-1])].astype(np.int32)
                out[offsets[1:] - 1] = -1
                yield pa.RecordBatch.from_arrays([pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(out))], ["codes"])

    return run


def _pairer(sent, most: int, parts: int):
    """Counted pairs of ids, h << 31 | t, sorted and compressed: a row for each number of words and part, into which all counts of a pair go."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = sent.value
        held: dict[int, tuple[np.ndarray, np.ndarray]] = {}

        def out() -> Iterator[pa.RecordBatch]:
            for step, (key, count) in held.items():
                mixed = (key.view(np.uint64) >> np.uint64(31)) * np.uint64(0x9E3779B97F4A7C15) + ((key & ((1 << 31) - 1)) >> 12).view(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F)
                part = ((mixed >> np.uint64(32)) % np.uint64(parts)).astype(np.int32)
                order = np.argsort(part, kind="stable")
                ends = np.searchsorted(part[order], np.arange(parts + 1))
                own = np.flatnonzero(ends[1:] > ends[:-1])
                key, count = key[order], count[order]
                each = [(_packed(np.diff(key[a:b], prepend=0)), _packed(count[a:b])) for a, b in zip(ends[own], ends[own + 1], strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(own, pa.int32()), pa.array(np.full(len(own), step), pa.int32()), pa.array(ends[own + 1] - ends[own], pa.int32()), pa.array([k for k, _ in each], pa.binary()), pa.array([c for _, c in each], pa.binary())], ["part", "d", "size", "keys", "counts"])

        for batch in batches:
            places = batch.column(1).to_numpy(zero_copy_only=False)
            for first, last, codes, owner in _chunks(batch, 0):
                at = _doubled(codes, tables)
                there = np.flatnonzero(at >= 0)
                for step in range(1, most + 1):
                    own = there[there + step < len(at)]
                    own = own[at[own + step] >= 0]
                    key, count = _summed((at[own] << 31) | at[own + step], places[first:last][owner[own]])
                    if step in held:
                        key, count = _summed(np.concatenate([held[step][0], key]), np.concatenate([held[step][1], count]))
                    if len(key):
                        held[step] = key, count
                if sum(len(k) for k, _ in held.values()) > 1_000_000:
                    yield from out()
                    held.clear()
        yield from out()

    return run


def _merger(min_support: int):
    """The pairs of a part that have the support."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[tuple[np.ndarray, np.ndarray]]] = {}
        settled: dict[int, int] = {}

        def settle(step: int) -> None:
            held[step] = [_summed(*(np.concatenate(x) for x in zip(*held[step], strict=True)))]
            settled[step] = len(held[step][0][0])

        for batch in batches:
            for step, size, keys, counts in zip(*(c.to_pylist() for c in batch.columns[1:]), strict=True):
                held.setdefault(step, []).append((np.cumsum(_unpacked(keys, size)), _unpacked(counts, size)))
                if sum(len(k) for k, _ in held[step]) > 2 * settled.get(step, 0) + 1_000_000:
                    settle(step)
        for step in sorted(held):
            settle(step)
            key, count = (x[held[step][0][1] >= min_support] for x in held[step][0])
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(key), step), pa.int32()), pa.array(key >> 31, pa.int32()), pa.array(key & ((1 << 31) - 1), pa.int32()), pa.array(count, pa.int64())], ["d", "h", "t", "c"])

    return run


def _found(batch: pa.RecordBatch, tables: list, size: int, wanted: np.ndarray | None = None) -> Iterator[tuple[int, int, np.ndarray, np.ndarray, np.ndarray]]:
    """first row, last row + 1, and of these the row (from 0), phrase and occurrences, a group of rows at a time.

    wanted: of each phrase whether it is to be found; ids grow with length, so no run longer than theirs is looked up.
    """
    last_id = size if wanted is None else int(np.flatnonzero(wanted)[-1]) if wanted.any() else -1
    for first, last, codes, owner in _chunks(batch, 1):
        at = codes.astype(np.int64)
        own = np.flatnonzero(at >= 0)
        keys = []

        def add(own: np.ndarray, ids: np.ndarray) -> None:
            if wanted is not None:
                own, ids = own[wanted[ids]], ids[wanted[ids]]
            keys.append(owner[own] * size + ids)  # noqa: B023

        add(own, at[own])
        for k, by_step in enumerate(tables):
            if by_step[0][1] > last_id:
                break
            longer = np.full(len(at), -1, np.int64)
            there = np.flatnonzero(at >= 0)
            for step, table in enumerate(by_step, 1):
                own = there[there + step < len(at)]
                own = own[at[own + step] >= 0]
                ids = _lookup(table, (at[own] << 31) | at[own + step])
                own, ids = own[ids >= 0], ids[ids >= 0]
                add(own, ids)
                if step == 1 << k:
                    longer[own] = ids
            at = longer
        key, count = np.unique(np.concatenate(keys), return_counts=True)
        yield first, last, key // size, key % size, count


def _ids(mined: Mined, phrases: DataFrame) -> DataFrame:
    """id, phrase of phrases among the mined ones; good_of, Mined.where and Mined.phrases give the ids along."""
    if "id" in phrases.columns:
        return phrases.select("id", "phrase")
    return mined.phrases.select("id", "phrase").join(phrases.select("phrase"), "phrase", "left_semi")


def counts_in_place(mined: Mined, phrases: DataFrame | None = None) -> DataFrame:
    """As phrase_counts, of these phrases among the mined ones (by default all of them), without a shuffle of texts."""
    if mined.codes is None:
        phrases = mined.phrases if phrases is None else phrases
        return phrase_counts(sentences_of(mined.by_doc), phrases, longest(phrases))
    sent, size, spelling, wanted = mined.sent, mined.size, mined.spelling, None
    if phrases is not None:
        mask = np.zeros(size, bool)
        mask[_ids(mined, phrases).select("id").toArrow().column("id").to_numpy()] = True
        wanted = phrases.sparkSession.sparkContext.broadcast(mask)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, last, row, phrase, count in _found(batch, sent.value, size, wanted and wanted.value):
                docs = batch.column(0).slice(first, last - first)
                for a, b in _pieces(_lengths(phrase, sent.value)):
                    own, place = np.unique(phrase[a:b], return_inverse=True)
                    yield pa.RecordBatch.from_arrays([docs.take(pa.array(row[a:b])), _spelled(own, sent.value, spelling.value).take(pa.array(place)), pa.array(count[a:b], pa.int64())], ["doc_id", "phrase", "c"])

    return mined.codes.mapInArrow(run, "doc_id bigint, phrase string, c bigint")


def words_by_tag(mined: Mined) -> DataFrame:
    """tag, term, c: occurrences of the frequent single words in the rows of each tag (by_document), but for rows without a doc_id.

    Summed where the documents are: what leaves a task is one count for each tag and word.
    """
    if mined.codes is None:
        each = mined.by_doc.where("doc_id is not null").select(F.explode("tags").alias("tag"), F.flatten("sents").alias("words")).select("tag", F.explode("words").alias("term"))
        return each.join(mined.phrases.where("n = 1").select(F.col("phrase").alias("term")), "term", "left_semi").groupBy("tag", "term").agg(F.count("*").alias("c"))
    starts = _starts(mined.sent.value)
    singles = max(int(starts[0]) if len(starts) else mined.size, 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        numbers: dict[str, int] = {}
        waiting: list[tuple[np.ndarray, np.ndarray]] = [(np.empty(0, np.int64), np.empty(0, np.int64))]

        def out() -> pa.RecordBatch:
            key, count = waiting[0]
            return pa.RecordBatch.from_arrays([pa.array(list(numbers), pa.string()).take(pa.array(key // singles)), pa.array(key % singles, pa.int32()), pa.array(count, pa.int64())], ["tag", "id", "c"])

        for batch in batches:
            for first, last, codes, owner in _chunks(batch, 1):
                tags = batch.column(2).slice(first, last - first)
                row = np.repeat(np.arange(last - first), pc.list_value_length(tags).to_numpy(zero_copy_only=False))
                tag = np.array([numbers.setdefault(t, len(numbers)) for t in tags.flatten().to_pylist()], np.int64)
                sizes = np.bincount(owner, minlength=last - first)
                many = sizes[row]
                code = codes[np.repeat((np.cumsum(sizes) - sizes)[row] - np.cumsum(many) + many, many) + np.arange(many.sum())]
                key = (np.repeat(tag, many) * singles + code)[code >= 0]
                waiting.append(np.unique(key, return_counts=True))
                if sum(len(k) for k, _ in waiting) > 1_000_000:
                    waiting[:] = [_summed(*(np.concatenate(x) for x in zip(*waiting, strict=True)))]
                    if len(waiting[0][0]) > 500_000:
                        yield out()
                        waiting[:] = [tuple(x[:0] for x in waiting[0])]
        waiting[:] = [_summed(*(np.concatenate(x) for x in zip(*waiting, strict=True)))]
        yield out()

    summed = _for_sums(mined.codes.where("doc_id is not null")).mapInArrow(run, "tag string, id int, c bigint").groupBy("tag", "id").agg(F.sum("c").alias("c"))
    return summed.join(mined.where("n = 1").select("id", F.col("phrase").alias("term")), "id").select("tag", "term", "c")


def probability_in_place(mined: Mined, phrases: DataFrame, shares: DataFrame, n_docs: int) -> DataFrame:
    """As phrase_probability of the topical counts of phrases (those among the mined ones) with these shares (phrase, path, share).

    A document's counts, their sums by node and their parts of them are made where the document is; what leaves a task is
    one sum for each phrase and node, in arrays.  A node's sums are its own, so more shares than are sent at once take a
    scan for each group of nodes.  Documents without a doc_id belong to no sum.
    """
    own = cut(phrases.select("phrase", F.lit(paths.ROOT).alias("path"), F.lit(1.0).alias("share")).union(shares.select("phrase", "path", "share")))
    many = {r.path: r.n for r in own.groupBy("path").agg(F.count("*").alias("n")).collect()}
    groups, room = [], 0
    for path in sorted(many):
        if not groups or many[path] > room:
            groups.append([])
            room = SHARES_SENT
        groups[-1].append(path)
        room -= many[path]
    if mined.codes is None or len(groups) > SCANS:
        counts = counts_in_place(mined, phrases).where("doc_id is not null")
        return phrase_probability(counts.join(own, "phrase").select("doc_id", "path", "phrase", (F.col("c") * F.col("share")).alias("c")), n_docs)
    names = _ids(mined, phrases)
    out = None
    for group in groups or [[paths.ROOT]]:
        numbers = F.broadcast(own.sparkSession.createDataFrame(list(enumerate(group)), "node int, path string"))
        table = own.join(names, "phrase").join(numbers, "path").select("id", "node", "share").toArrow().sort_by([("id", "ascending"), ("node", "ascending")])
        summed = _summed_shares(mined, *(table.column(c).to_numpy() for c in ("id", "node", "share")), len(group)).join(numbers, "node").select("id", "path", (F.col("p") / n_docs).alias("p"))
        out = summed if out is None else out.union(summed)
    return out.join(names, "id").select("path", "phrase", "p")


def _summed_shares(mined: Mined, at: np.ndarray, node: np.ndarray, share: np.ndarray, width: int) -> DataFrame:
    """id, node, p: the documents' parts summed over all of them.  at, node, share: sorted by id and node, which are below width."""
    spark = mined.codes.sparkSession
    begins = np.searchsorted(at, np.arange(mined.size + 1)).astype(np.int64)
    parts = _partitions(spark)
    cuts = np.linspace(0, len(share), parts + 1).astype(np.int64)
    words, size, weights = mined.sent, mined.size, spark.sparkContext.broadcast((begins, node.astype(np.int32), share))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        begins, node, share = weights.value
        sums, seen, wanted = np.zeros(len(share)), np.zeros(len(share), bool), begins[1:] > begins[:-1]
        for batch in batches:
            for _, _, row, phrase, count in _found(batch, words.value, size, wanted):
                many = begins[phrase + 1] - begins[phrase]
                entry = np.repeat(begins[phrase] - np.cumsum(many) + many, many) + np.arange(many.sum())
                c = np.repeat(count, many) * share[entry]
                group = np.repeat(row, many) * width + node[entry]
                total = np.bincount(group, c)[group] if len(group) else c
                some = total > 0
                entry = entry[some]
                np.add.at(sums, entry, c[some] / total[some])
                seen[entry] = True
        for part, (a, b) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)):
            if seen[a:b].any():
                yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([np.packbits(seen[a:b]).tobytes()], pa.binary()), pa.array([_packed(sums[a:b][seen[a:b]])], pa.binary())], ["part", "seen", "sums"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        begins, node, _ = weights.value
        held: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        for batch in batches:
            for part, there, sums in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                n = int(cuts[part + 1] - cuts[part])
                seen, total = held.setdefault(part, (np.zeros(n, bool), np.zeros(n)))
                there = np.unpackbits(np.frombuffer(there, np.uint8), count=n).astype(bool)
                total[there] += _unpacked(sums, int(there.sum()), np.float64)
                seen |= there
        for part, (seen, total) in held.items():
            entry = np.flatnonzero(seen) + cuts[part]
            yield pa.RecordBatch.from_arrays([pa.array(np.searchsorted(begins, entry, "right") - 1, pa.int32()), pa.array(node[entry], pa.int32()), pa.array(total[seen])], ["id", "node", "p"])

    made = _for_sums(mined.codes.where("doc_id is not null")).mapInArrow(run, "part int, seen binary, sums binary")
    return made.repartitionById(parts, F.col("part")).mapInArrow(add, "id int, node int, p double")


def phrase_posterior(phrases: DataFrame, words: DataFrame, nodes: DataFrame) -> DataFrame:
    """phrase, path, share: the posterior over each parent's children of a whole phrase, by the product of its words' probabilities.

    words: path, term, phi; nodes: path, parent, alpha of one level.  It does not depend on the document, so it is
    computed once for each phrase.  Products are sums of logarithms; a word that a topic lacks rules the topic out.
    Where phrases have ids, a word's row carries the id and not the phrase, which may be thousands of words long.
    """
    key = "id" if "id" in phrases.columns else "phrase"
    terms = phrases.select(key, F.size(F.split("phrase", " ")).alias("size"), F.explode(F.split("phrase", " ")).alias("term"))
    topics = F.broadcast(nodes.select("path", "parent", "alpha"))  # a row for each node
    likely = words.where("phi > 0").select("path", "term", "phi")
    likely = F.broadcast(likely) if likely.count() <= PHRASES_BROADCAST else likely
    scored = terms.join(likely, "term").groupBy(key, "size", "path").agg(F.sum(F.log("phi")).alias("lp"), F.count("*").alias("found"))
    possible = scored.where("found = size").join(topics, "path").withColumn("lp", F.col("lp") + F.log("alpha"))
    own = Window.partitionBy(key, "parent")
    weight = F.exp(F.col("lp") - F.max("lp").over(own))
    shares = possible.withColumn("weight", weight).select(key, "path", (F.col("weight") / F.sum("weight").over(own)).alias("share"))
    return (shares.join(phrases.select("id", "phrase"), "id") if key == "id" else shares).select("phrase", "path", "share")


def path_shares(posterior: DataFrame, height: int) -> DataFrame:
    """phrase, path, share of every node but the root: the product of the posteriors along its path."""
    level = paths.level(F.col("path"))
    out = last = posterior.where(level == 1)
    for k in range(2, height + 1):
        above = last.select("phrase", F.col("path").alias("parent"), F.col("share").alias("above"))
        last = posterior.where(level == k).withColumn("parent", paths.parent(F.col("path"))).join(above, ["phrase", "parent"]).select("phrase", "path", (F.col("share") * F.col("above")).alias("share"))
        out = out.union(last)
    return out


def topical_phrase_counts(counts: DataFrame, posterior: DataFrame, height: int = 1) -> DataFrame:
    """doc_id, path, phrase, c for the root (plain counts) and the nodes below it (counts times the posteriors along the path)."""
    below = counts.join(path_shares(posterior, height), "phrase").select("doc_id", "path", "phrase", (F.col("c") * F.col("share")).alias("c"))
    return counts.select("doc_id", F.lit(paths.ROOT).alias("path"), "phrase", F.col("c").cast("double").alias("c")).union(below)


def phrase_probability(topical: DataFrame, n_docs: int) -> DataFrame:
    """path, phrase, p: the mean over all documents of a phrase's share of the topic's phrases; documents without any add 0."""
    total = F.sum("c").over(Window.partitionBy("doc_id", "path"))  # a document's rows: one shuffle, nothing is written twice
    return topical.withColumn("total", total).where("total > 0").groupBy("path", "phrase").agg((F.sum(F.col("c") / F.col("total")) / n_docs).alias("p"))


def rank_phrases(probability: DataFrame, top: int | None = None, by: str = "both") -> DataFrame:
    """path, rank, phrase, p_topic, p_parent, score of all nodes but the root.

    popularity: p; ratio: ln(p / parent's p); both: their product.  Where a p is 0 (of long phrases, shares may be too small
    for a double) there is no ratio: such rows have no score by it and come last.
    """
    above = probability.select(F.col("path").alias("parent"), "phrase", F.col("p").alias("p_parent"))
    joined = probability.withColumn("parent", paths.parent(F.col("path"))).where("parent is not null").join(above, ["parent", "phrase"])
    ratio = F.log(F.try_divide("p", "p_parent"))
    score: Column = {"popularity": F.col("p"), "ratio": ratio, "both": F.col("p") * ratio}[by]
    scored = joined.select("path", "phrase", F.col("p").alias("p_topic"), "p_parent", score.alias("score"))
    ranked = scored.withColumn("rank", F.row_number().over(Window.partitionBy("path").orderBy(F.round("score", 12).desc(), "phrase")))
    if top is not None:
        ranked = ranked.where(F.col("rank") <= top)
    return ranked.select("path", "rank", "phrase", "p_topic", "p_parent", "score")


def collapse_plurals(ranked: DataFrame) -> DataFrame:
    """Of phrases that differ in a final s only, the best ranked of each topic; ranks are numbered anew."""
    key = F.regexp_replace("phrase", "s$", "")
    best = ranked.withColumn("key", key).withColumn("k", F.row_number().over(Window.partitionBy("path", "key").orderBy("rank"))).where("k = 1")
    return best.withColumn("rank", F.row_number().over(Window.partitionBy("path").orderBy("rank"))).drop("key", "k").select(ranked.columns)


def n_tokens_of(by_doc: DataFrame) -> int:
    """Words of all sentences, at least 1."""
    return max(by_doc.agg(F.sum(F.size(F.flatten("sents")))).first()[0] or 0, 1)


def rank_tree(rows: DataFrame | Mined, nodes: DataFrame, words: DataFrame, n_docs: int, *, min_support: int = 1, max_len: int | None = None, top: int | None = None, by: str = "both") -> DataFrame:
    """Phrases of a whole tree: mined, filtered by quality, counted by topic and ranked under every parent at once.

    rows: as by_document gives them, or sentences (doc_id, sent_no, words), or what has been mined of them already;
    nodes: path, parent, alpha; words: path, term, phi.  Result as rank_phrases.
    """
    if isinstance(rows, DataFrame) and "sents" not in rows.columns:
        rows = stored(rows.groupBy("doc_id").agg(F.collect_list("words").alias("sents")), "sentences")
    mined = rows if isinstance(rows, Mined) else mine(rows, min_support, max_len)
    known = cut(good_of(mined))
    height = nodes.agg(F.max(paths.level(F.col("path")))).first()[0] or 0
    shares = cut(phrase_posterior(known, words, nodes.where("parent is not null")))
    return rank_phrases(cut(probability_in_place(mined, known, path_shares(shares, height), n_docs)), top, by)

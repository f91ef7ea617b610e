"""Benchmark decontamination: CGK embedding, bit-sampling LSH over item-sized windows, exact edit verification.

A random walk reads a word sequence: at each step it emits the word under its pointer and a hash of (step, word)
decides whether the pointer moves on.  Sequences at a small edit distance then emit the same word at most steps, so
edit distance becomes Hamming distance.  REPEATS times for each of WALKS walks, SAMPLED steps are drawn from the
steps that an item of a length class covers; equal samples make a window of a document a candidate for an item, and the
semi-global edit distance of the item to the text around its windows decides, exactly.

Windows begin at every STRIDE-th word.  Each item is entered once for each of 2 * STRIDE leading words left out, so any
alignment has two windows that begin at exactly such a word: the stride costs no recall.  Walks are prefix-closed, so
one walk over a window serves items of all lengths.

Scattered wrong letters spoil most words, and a missing head moves the start, so characters are a second entry: runs
of 5 to 8 characters that document and item share are counted along diagonals, over the whole item.  A stretch with
enough of them near one diagonal is a candidate too, and the same edit distance decides.

Before the distance is worked out, trigrams are counted: a text within k edits of an item of m characters holds at least
m - 2 - 3k of its trigrams, so what has fewer is sent away without loss.  Items under LEAST_WORDS words leave no room for
an edit of a whole word and are looked up as exact runs of words.

Items are the query set: their keys are sent to the workers ITEMS_AT_ONCE at a time, one pass over the documents each.

Defined results: null texts count as empty; items without words match nothing, those of fewer than LEAST_WORDS words
match their exact words, or by similarity if one word has UNSPACED characters; words are lower-cased
runs of letters, digits and non-ASCII characters; repeated items and rows are matched alike; a document matches an item
once, at its best place (the first of equals); empty tables give no rows.  Other input columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import reduce
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from momenttree.llm.runtime import ship

SIMILARITY = 0.8
LEAST_WORDS = 5
#: An item of fewer words enters, by characters only, if one of them is so long: it is written without spaces.
UNSPACED = 15
STRIDE = 4
WALKS = 2
REPEATS = 16
SAMPLED = 4
ITEMS_AT_ONCE = 5_000
TABLE_BITS = 22
#: Bits of the tables, one for each sampled key: small enough for a core's cache while the entries are few.
KEY_BITS = (16, 20)
#: Length of the runs of characters that are counted before the exact check.
COUNTED = 3
DOCS_AT_ONCE = 400
#: Fewest words of each length class; the first class has windows at every word and leaves nothing out.
CLASSES = (5, 12, 18, 28, 42, 64, 96)
#: Character entry: from so many characters of an item on, the gram length and the share of the item's grams that have to lie near one diagonal.
GRAMS = ((0, 5, 0.12), (70, 7, 0.10), (130, 8, 0.08))
#: Width in characters of a band of diagonals; two adjacent bands count together.
BAND = 32
#: Before the exact check, a stretch has to hold so large a share of the item's distinct runs of CHECKED characters; items under CHECKED_FROM characters pass.
CHECKED, CHECKED_SHARE, CHECKED_FROM = 6, 0.12, 100
_BASE = 0x01000193
_WORDS = re.compile(rb"[0-9A-Za-z\x80-\xff]+").findall


def words_of(text: str) -> list[bytes]:
    return _WORDS(text.lower().encode("utf-8", "surrogatepass"))


def hashed(words: list[bytes]) -> np.ndarray:
    """Non-zero 32-bit hash of each word."""
    return np.fromiter(map(crc32, words), np.uint32, len(words)) | np.uint32(1)


def left_outs(class_no: int) -> int:
    """How many numbers of leading words are left out: two aligned windows for items that are long enough, else one."""
    return 1 if class_no == 0 else STRIDE if CLASSES[class_no] < 4 * STRIDE else 2 * STRIDE


def walk_length(class_no: int) -> int:
    """Steps that the shortest item of a class, less what is left out, almost surely does not end within."""
    low = CLASSES[class_no]
    return low if class_no == 0 else int(1.3 * (low - left_outs(class_no) + 1))


def walks() -> np.ndarray:
    """Odd multipliers for (walk, step): the top bit of word hash times multiplier moves the pointer."""
    random = np.random.default_rng(91)
    return random.integers(0, 1 << 31, (WALKS, walk_length(len(CLASSES) - 1)), dtype=np.uint32) * np.uint32(2) + np.uint32(1)


def samples(class_no: int) -> np.ndarray:
    """(WALKS, REPEATS, SAMPLED) steps of one class, one from each equal part of the walk, since a word may last several steps."""
    random = np.random.default_rng(1000 + class_no)
    edges = np.linspace(0, walk_length(class_no), SAMPLED + 1).astype(int)
    return np.stack([random.integers(edges[k], edges[k + 1], (WALKS, REPEATS)) for k in range(SAMPLED)], axis=-1)


def embed(flat: np.ndarray, starts: np.ndarray, multipliers: np.ndarray, steps: int) -> np.ndarray:
    """(steps, windows) emitted words.  A zero in flat ends a sequence: the pointer never leaves it."""
    at = starts.copy()
    out = np.empty((steps, len(starts)), np.uint32)
    for step in range(steps):
        word = flat.take(at, out=out[step])
        at += (word * multipliers[step]) >> np.uint32(31)
    return out


def keys(emitted: np.ndarray, steps: np.ndarray, salt: int) -> np.ndarray:
    """One 32-bit key a window from the sampled steps."""
    key = np.full(emitted.shape[1], salt, np.uint32)
    for s in steps:
        key ^= emitted[s]
        key *= np.uint32(0x85EBCA6B)
        key ^= key >> np.uint32(15)
    return key


def edit_distance_within(item: str, text: str) -> tuple[int, int]:
    """Least edit distance of item to any stretch of text, and where that stretch ends: bit-parallel columns."""
    m = len(item)
    if not m:
        return 0, 0
    rows: dict[str, int] = {}
    for k, c in enumerate(item):
        rows[c] = rows.get(c, 0) | 1 << k
    top, full = 1 << (m - 1), (1 << m) - 1
    up, down, distance = full, 0, m
    best, end = m, 0
    for j, c in enumerate(text, 1):
        eq = rows.get(c, 0)
        x = (((eq & up) + up) ^ up) | eq | down
        grow, fall = down | (full & ~(x | up)), up & x
        if grow & top:
            distance += 1
        elif fall & top:
            distance -= 1
        grow, fall = (grow << 1) & full, (fall << 1) & full
        up, down = fall | (full & ~(x | grow)), grow & x
        if distance < best:
            best, end = distance, j
    return best, end


#: Items of at most so many machine words of 64 characters are compared many at a time, and only from so many pairs on.
WORDS_AT_ONCE, PAIRS_FROM = 8, 24


def row_masks(item: str) -> tuple[np.ndarray, np.ndarray]:
    """The distinct characters of an item, sorted, and for each the bits of its places (a last row of zeros for any other)."""
    codes = characters(item)
    distinct, place = np.unique(codes, return_inverse=True)
    at = np.arange(len(codes))
    masks = np.zeros((len(distinct) + 1, -(-len(codes) // 64)), np.uint64)
    np.bitwise_or.at(masks, (place, at // 64), np.uint64(1) << (at % 64).astype(np.uint64))
    return distinct, masks


def edit_distances(pairs: list[tuple[str, tuple[np.ndarray, np.ndarray], str]]) -> list[tuple[int, int]]:
    """edit_distance_within for (item, its row_masks, text), all pairs a column at a time; items of one number of machine words."""
    n, width = len(pairs), pairs[0][1][1].shape[1]
    longest = max(len(t) for _, _, t in pairs)
    eq_at = np.zeros((longest, n), np.int64)
    at = 0
    for k, (_, (distinct, masks), text) in enumerate(pairs):
        codes = characters(text)
        place = np.minimum(distinct.searchsorted(codes), len(distinct) - 1)
        eq_at[:, k] = at + len(distinct)  # what follows a text equals nothing, which never lowers a distance
        eq_at[: len(codes), k] = at + np.where(distinct[place] == codes, place, len(distinct))
        at += len(masks)
    flat = np.concatenate([masks for _, (_, masks), _ in pairs]).T.copy()
    size = np.array([len(i) for i, _, _ in pairs])
    top, one, sign = ((size - 1) % 64).astype(np.uint64), np.uint64(1), np.uint64(63)
    up, down = np.full((width, n), ~np.uint64(0)), np.zeros((width, n), np.uint64)
    distance, best, end = size.copy(), size.copy(), np.zeros(n, np.int64)
    for j in range(longest):
        grow_in = fall_in = np.zeros(n, np.uint64)
        for w in range(width):
            eq, u, d = flat[w].take(eq_at[j]), up[w], down[w]
            x = eq | d
            eq |= fall_in
            h = (((eq & u) + u) ^ u) | eq
            grow, fall = d | ~(h | u), u & h
            if w == width - 1:
                distance += ((grow >> top) & one).astype(np.int64) - ((fall >> top) & one).astype(np.int64)
            grow_out, fall_out = grow >> sign, fall >> sign
            grow, fall = (grow << one) | grow_in, (fall << one) | fall_in
            up[w], down[w] = fall | ~(x | grow), grow & x
            grow_in, fall_in = grow_out, fall_out
        better = distance < best
        if better.any():
            best[better], end[better] = distance[better], j + 1
    return list(zip(best.tolist(), end.tolist(), strict=True))


def gram_hashes(codes: np.ndarray, q: int) -> np.ndarray:
    """32-bit hash of the q characters from each place on."""
    if len(codes) < q:
        return np.empty(0, np.uint32)
    powers = [np.uint32(pow(_BASE, k, 1 << 32)) for k in range(q)]
    size, made, whole, left = 1, codes, None, q
    while True:  # runs of 1, 2, 4, ... characters; those that the bits of q name are put together
        if left & 1:
            whole, done = (made, size) if whole is None else (made[: len(made) - done] * powers[done] + whole[size:], size + done)
        left >>= 1
        if not left:
            return (whole ^ (whole >> np.uint32(15))) * np.uint32(0x85EBCA6B)
        made, size = made[:-size] * powers[size] + made[size:], 2 * size


def characters(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)


@dataclass
class GramEntry:
    """The grams of all items of one length class, in sorted order, with item and place."""

    q: int
    known: np.ndarray
    items: np.ndarray
    places: np.ndarray
    table: np.ndarray

    @classmethod
    def build(cls, texts: list[str], chosen: list[int], q: int) -> GramEntry:
        made = [gram_hashes(characters(texts[k]), q) for k in chosen]
        sizes = [len(x) for x in made]
        known = np.concatenate(made)
        order = np.argsort(known, kind="stable")
        table = np.zeros(1 << TABLE_BITS, bool)
        table[known >> np.uint32(32 - TABLE_BITS)] = True
        return cls(q, known[order], np.repeat(np.array(chosen, np.int64), sizes)[order], np.concatenate([np.arange(n) for n in sizes])[order], table)

    def candidates(self, codes: np.ndarray, firsts: np.ndarray, least: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Document, item and character at which the item would begin, of bands with at least least[item] equal grams."""
        made = gram_hashes(codes, self.q)
        at = np.flatnonzero(self.table[made >> np.uint32(32 - TABLE_BITS)])
        low = np.searchsorted(self.known, made[at], "left")
        n = np.searchsorted(self.known, made[at], "right") - low
        entry = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + np.repeat(low, n)
        doc = np.searchsorted(firsts, at, "right") - 1
        begin = np.repeat(at - firsts[doc], n) - self.places[entry]
        reach = int(self.places.max(initial=0)) // BAND + 2
        band, counts = np.unique((np.repeat(doc, n) * len(least) + self.items[entry] << 27) + begin // BAND + reach, return_counts=True)
        after = np.append(np.where(np.diff(band) == 1, counts[1:], 0), 0) if len(band) else counts
        band = band[counts + after >= least[(band >> 27) % len(least)]]
        doc, item = np.divmod(band >> 27, len(least))
        return doc, item, ((band & (1 << 27) - 1) - reach) * BAND


@dataclass
class ItemIndex:
    """Sampled keys of all items with what they stand for."""

    ids: list[int]
    texts: list[str]
    sizes: list[int]
    classes: list[int] = field(default_factory=list)
    owners: dict[int, np.ndarray] = field(default_factory=dict)  # class -> (entries, 2): item, words left out
    found: dict[tuple[int, int, int], tuple[np.ndarray, np.ndarray, np.ndarray]] = field(default_factory=dict)  # (class, walk, repeat) -> sorted keys, their entries, bit table of the keys
    counted: list[tuple[np.ndarray, np.ndarray]] = field(default_factory=list)  # of each item, its runs of COUNTED characters and how often
    masks: list[tuple[np.ndarray, np.ndarray] | None] = field(default_factory=list)  # row_masks of items that are compared many at a time
    short: dict[int, dict[tuple[bytes, ...], list[int]]] = field(default_factory=dict)  # words -> exact words -> items
    grams: list[GramEntry] = field(default_factory=list)
    runs: list[np.ndarray] = field(default_factory=list)  # of each item, hashes of its runs of CHECKED characters, sorted
    least: np.ndarray | None = None  # equal grams that the character entry asks for, by item

    @classmethod
    def build(cls, items: list[tuple[int, str]]) -> ItemIndex:
        split = [(i, w) for i, t in items if (w := words_of(t or ""))]
        whole = lambda w: len(w) >= LEAST_WORDS or any(len(x.decode("utf-8", "replace")) >= UNSPACED for x in w)
        kept = [(i, w) for i, w in split if whole(w)]
        few = [(i, w) for i, w in split if not whole(w)]
        index = cls([i for i, _ in kept + few], [b" ".join(w).decode("utf-8", "replace") for _, w in kept + few], [len(w) for _, w in kept + few])
        for k, (_, w) in enumerate(few, len(kept)):
            index.short.setdefault(len(w), {}).setdefault(tuple(w), []).append(k)
        if not kept:
            return index
        index.enter_grams(len(kept))
        flat, starts, owners, at = [], [], [], 0
        for k, (_, w) in enumerate(kept):
            class_no = sum(len(w) >= c for c in CLASSES) - 1
            flat += [hashed(w), np.zeros(1, np.uint32)]
            for left_out in range(left_outs(class_no) if class_no >= 0 else 0):
                starts.append(at + left_out)
                owners.append((class_no, k, left_out))
            at += len(w) + 1
        index.classes = sorted({c for c, _, _ in owners})
        flat, starts, of_class = np.concatenate(flat), np.array(starts, np.int64), np.array([c for c, _, _ in owners])
        for class_no in index.classes:
            own = np.flatnonzero(of_class == class_no)
            index.owners[class_no] = np.array([owners[o][1:] for o in own], np.int64)
            drawn = samples(class_no)
            for walk, multipliers in enumerate(walks()):
                emitted = embed(flat, starts[own], multipliers, walk_length(class_no))
                for repeat in range(REPEATS):
                    made = keys(emitted, drawn[walk, repeat], index.salt(class_no, walk, repeat))
                    order = np.argsort(made, kind="stable")
                    bits = min(max((16 * len(made)).bit_length(), KEY_BITS[0]), KEY_BITS[1])
                    table = np.zeros(1 << bits, bool)
                    table[made >> np.uint32(32 - bits)] = True
                    index.found[class_no, walk, repeat] = made[order], order, table
        return index

    def enter_grams(self, n: int) -> None:
        """The character entry and the counts of the first n items."""
        texts = self.texts[:n]
        lengths = np.array([len(t) for t in texts])
        rule = np.searchsorted([low for low, _, _ in GRAMS], lengths, "right") - 1
        self.least = np.maximum(2, np.array([GRAMS[r][2] for r in rule]) * lengths).astype(np.int64)
        self.runs = [np.unique(gram_hashes(characters(t if len(t) >= CHECKED_FROM else ""), CHECKED)) for t in texts]
        self.counted = [np.unique(gram_hashes(characters(t), COUNTED), return_counts=True) for t in texts]
        self.masks = [row_masks(t) if len(t) <= 64 * WORDS_AT_ONCE else None for t in texts]
        self.grams = [GramEntry.build(texts, np.flatnonzero(rule == r).tolist(), q) for r, (_, q, _) in enumerate(GRAMS) if (rule == r).any()]

    def by_characters(self, plain: list[str]) -> Iterator[tuple[int, int, int, str]]:
        """(document, item, first character, text) of stretches that share enough grams with an item near one diagonal."""
        firsts = np.cumsum([0, *(len(t) + 1 for t in plain)])[:-1]
        codes = characters("\n".join(plain))
        runs = gram_hashes(codes, CHECKED)
        for entry in self.grams:
            last = (-1, -1, 0)
            for doc, item, begin in zip(*(x.tolist() for x in entry.candidates(codes, firsts, self.least)), strict=True):
                margin = len(self.texts[item]) // 4 + BAND
                low, high = max(0, begin - margin), max(0, begin + 2 * BAND + len(self.texts[item]) + margin)
                if last == (doc, item, begin - BAND):  # the band before has been looked at, with more text around than this one needs
                    last = (-1, -1, 0)
                    continue
                last = (doc, item, begin)
                if len(own := self.runs[item]):
                    here = runs[firsts[doc] + low : firsts[doc] + min(high, len(plain[doc]))]
                    at = own.searchsorted(here)
                    if len(set(at[own.take(at, mode="clip") == here].tolist())) < CHECKED_SHARE * len(own):
                        continue
                yield doc, item, low, plain[doc][low:high]

    @staticmethod
    def salt(class_no: int, walk: int, repeat: int) -> int:
        return (class_no * 8191 + walk * 131 + repeat * 7 + 1) * 0x9E3779B1 & 0xFFFFFFFF

    def candidates(self, flat: np.ndarray, firsts: np.ndarray, sizes: np.ndarray) -> Iterator[np.ndarray]:
        """(document, item, word at which the item would begin) of colliding windows as columns, repeats included."""
        multipliers = walks()
        for stride, classes in ((1, [c for c in self.classes if c == 0]), (STRIDE, [c for c in self.classes if c])):
            if not classes:
                continue
            windows = -(-sizes // stride)
            owner = np.repeat(np.arange(len(sizes)), windows)
            offset = (np.arange(len(owner)) - np.repeat(np.cumsum(windows) - windows, windows)) * stride
            starts = firsts[owner] + offset
            for walk in range(WALKS):
                emitted = embed(flat, starts, multipliers[walk], walk_length(classes[-1]))
                for class_no in classes:
                    drawn = samples(class_no)
                    pairs = [self.collisions(keys(emitted, drawn[walk, repeat], self.salt(class_no, walk, repeat)), class_no, walk, repeat) for repeat in range(REPEATS)]
                    window, entry = np.divmod(np.unique(np.concatenate(pairs)), len(self.owners[class_no]))
                    items, left_out = self.owners[class_no][entry].T
                    yield np.stack([owner[window], items, offset[window] - left_out])

    def collisions(self, made: np.ndarray, class_no: int, walk: int, repeat: int) -> np.ndarray:
        """window * entries + entry of all equal keys: a bit table sorts out nearly all windows, the sorted keys the rest."""
        known, entries, table = self.found[class_no, walk, repeat]
        hits = np.flatnonzero(table[made >> np.uint32(33 - len(table).bit_length())])
        found = made[hits]
        low, high = np.searchsorted(known, found, "left"), np.searchsorted(known, found, "right")
        n = high - low
        place = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + np.repeat(low, n)
        return np.repeat(hits, n) * len(entries) + entries[place]

    def by_walks(self, words: list[list[bytes]], plain: list[str]) -> Iterator[tuple[int, int, int, str]]:
        """(document, item, first character, text) around colliding windows; those whose surroundings overlap become one stretch."""
        sizes = np.array([len(w) for w in words], np.int64)
        firsts = np.cumsum(sizes + 1) - sizes - 1
        stop = np.zeros(1, np.uint32)
        flat = np.concatenate([x for w in words for x in (hashed(w), stop)])
        met = [x for x in self.candidates(flat, firsts, sizes) if x.size]
        if not met:
            return
        doc, item, begin = np.concatenate(met, axis=1)
        order = np.lexsort((begin, item, doc))
        doc, item, begin = doc[order], item[order], begin[order]
        room = np.maximum(2, np.array(self.sizes, np.int64)[item] // 4)
        fresh = np.append(True, (np.diff(doc) != 0) | (np.diff(item) != 0) | (np.diff(begin) > room[1:]))
        first = np.flatnonzero(fresh)
        last = np.append(first[1:], len(doc)) - 1
        joined = "\n".join(plain)
        edges = np.append(np.append(0, np.flatnonzero(characters(joined) <= 32) + 1), len(joined) + 1)  # where each word begins
        before = np.cumsum(np.maximum(sizes, 1)) - np.maximum(sizes, 1)  # an empty text is one empty word
        begins = edges[before]
        low, high = np.maximum(begin[first] - room[first], 0), np.minimum(begin[last] + np.array(self.sizes)[item[first]] + room[first], sizes[doc[first]])
        low, high = edges[before[doc[first]] + low], edges[before[doc[first]] + np.maximum(low, high)] - 1
        for d, i, a, b in zip(*(x.tolist() for x in (doc[first], item[first], low, high)), strict=True):
            yield d, i, a - int(begins[d]), joined[a:b]

    def may_hold(self, item: int, text: str, most: int) -> bool:
        """Whether text has the trigrams that any stretch of it within `most` edits of the item would have."""
        runs, times = self.counted[item]
        least = len(self.texts[item]) - COUNTED + 1 - COUNTED * most
        if least <= 0:
            return True
        here = np.sort(gram_hashes(characters(text), COUNTED))
        there = here.searchsorted(runs, "right") - here.searchsorted(runs, "left")
        return int(np.minimum(there, times).sum()) >= least

    def matches(self, texts: list[str], similarity: float) -> list[dict[int, tuple[int, int]]]:
        """For each text: item -> (edit distance, word near which the item begins) of those that verify."""
        words = [words_of(t) for t in texts]
        out: list[dict[int, tuple[int, int]]] = [{} for _ in texts]
        if not texts or not self.texts:
            return out
        for doc, own in enumerate(words):
            for n, known in self.short.items():
                for k in range(len(own) - n + 1):
                    for item in known.get(tuple(own[k : k + n]), ()):
                        out[doc].setdefault(item, (0, k))
        if not self.counted:
            return out
        plain = [b" ".join(w).decode("utf-8", "replace") for w in words]
        for stretches in (self.by_walks(words, plain), self.by_characters(plain)):
            open_ = []
            for doc, item, low, around in stretches:
                whole = around.find(self.texts[item])
                if whole >= 0:
                    if out[doc].get(item, (1, 0))[0]:
                        out[doc][item] = 0, plain[doc][: low + whole].count(" ")
                elif self.may_hold(item, around, self.most(item, similarity)):
                    open_.append((doc, item, low, around))
            open_ = [x for x in open_ if out[x[0]].get(x[1], (1, 0))[0]]
            for (doc, item, low, _), (distance, end) in zip(open_, self.distances([(item, around) for _, item, _, around in open_]), strict=True):
                best = out[doc].get(item)
                if distance <= self.most(item, similarity) and (best is None or distance < best[0]):
                    out[doc][item] = distance, plain[doc][: max(0, low + end - len(self.texts[item]))].count(" ")
        return out

    def most(self, item: int, similarity: float) -> int:
        return int((1 - similarity) * len(self.texts[item]) + 1e-9)

    def distances(self, pairs: list[tuple[int, str]]) -> list[tuple[int, int]]:
        """edit_distance_within of (item, text) pairs, those of short items many at a time."""
        out: list[tuple[int, int]] = [(0, 0)] * len(pairs)
        groups: dict[int, list[int]] = {}
        for k, (item, _) in enumerate(pairs):
            groups.setdefault(0 if self.masks[item] is None else self.masks[item][1].shape[1], []).append(k)
        for width, own in groups.items():
            own.sort(key=lambda k: len(pairs[k][1]))
            for at in range(0, len(own), 512):
                part = own[at : at + 512]
                if width and len(part) >= PAIRS_FROM:
                    found = edit_distances([(self.texts[pairs[k][0]], self.masks[pairs[k][0]], pairs[k][1]) for k in part])
                else:
                    found = [edit_distance_within(self.texts[pairs[k][0]], pairs[k][1]) for k in part]
                for k, x in zip(part, found, strict=True):
                    out[k] = x
        return out


def _indexes(items: DataFrame, id_col: str, text_col: str) -> list[ItemIndex]:
    """The query set in blocks, in order of id; a block's keys are of bounded size."""
    rows = items.select(F.col(id_col).cast("bigint").alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text")).where("id is not null").orderBy("id", "text")
    blocks, block = [], []
    for row in rows.toLocalIterator():
        block.append((row.id, row.text))
        if len(block) == ITEMS_AT_ONCE:
            blocks.append(ItemIndex.build(block))
            block = []
    return [*blocks, ItemIndex.build(block)] if block else blocks


def _slices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for at in range(0, batch.num_rows, DOCS_AT_ONCE):
            yield batch.slice(at, DOCS_AT_ONCE)


def leaks(docs: DataFrame, items: DataFrame, *, item_id: str = "item_id", item_text: str = "text", similarity: float = SIMILARITY) -> DataFrame:
    """doc_id, item_id, first_word, edit_distance, item_chars of every document and item that match.  No shuffle."""
    spark = docs.sparkSession
    ship(spark)
    chosen = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text"))
    ddl = "doc_id bigint, item_id bigint, first_word bigint, edit_distance bigint, item_chars bigint"

    def searched(index: ItemIndex) -> DataFrame:
        sent = spark.sparkContext.broadcast(index)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            known = sent.value
            for batch in _slices(batches):
                ids = batch.column(0).to_pylist()
                found = known.matches([x or "" for x in batch.column(1).to_pylist()], similarity)
                rows = [(ids[k], known.ids[i], max(0, begin), distance, len(known.texts[i])) for k, own in enumerate(found) for i, (distance, begin) in sorted(own.items())]
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], ["doc_id", "item_id", "first_word", "edit_distance", "item_chars"])

        return chosen.mapInArrow(run, ddl)

    indexes = _indexes(items, item_id, item_text)
    return reduce(DataFrame.union, map(searched, indexes)) if indexes else spark.createDataFrame([], ddl)


def drop_leaks(docs: DataFrame, items: DataFrame, *, item_id: str = "item_id", item_text: str = "text", similarity: float = SIMILARITY) -> DataFrame:
    """The rows of docs that match no item, all columns kept.  No shuffle."""
    spark = docs.sparkSession
    ship(spark)
    at = docs.columns.index("text")
    for index in _indexes(items, item_id, item_text):
        sent = spark.sparkContext.broadcast(index)

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            for batch in _slices(batches):
                found = sent.value.matches([x or "" for x in batch.column(at).to_pylist()], similarity)
                yield batch.filter(pa.array([not own for own in found], pa.bool_()))

        docs = docs.mapInArrow(run, docs.schema)
    return docs

"""Candidates for benchmark items whose start or whose letters are changed, all within the similarity."""

import random

import numpy as np
import pytest

from momenttree.llm import decontaminate

LETTERS = "abcdefghijklmnopqrstuvwxyz"


def items_of(n_words, n=120):
    r = random.Random(n_words)
    return [(k, " ".join("".join(r.choice(LETTERS) for _ in range(r.randrange(2, 10))) for _ in range(n_words))) for k in range(n)]


def recall(items, changed):
    r = random.Random(7)
    texts = [" ".join(["filler"] * r.randrange(1, 6) + [changed(r, text), "more words"]) for _, text in items]
    index = decontaminate.ItemIndex.build(items)
    return np.mean([k in {index.ids[i] for i in f} for (k, _), f in zip(items, index.matches(texts, decontaminate.SIMILARITY), strict=True)])


@pytest.mark.parametrize("n_words", [5, 8, 11, 15, 40, 58, 150])
@pytest.mark.parametrize("share", [0.1, 0.18])
def test_items_without_their_head(n_words, share):
    assert recall(items_of(n_words), lambda r, t: t[int(share * len(t)) :]) == 1


@pytest.mark.parametrize("n_words", [8, 11])
def test_short_items_with_another_first_word(n_words):
    items = [(k, t) for k, t in items_of(n_words) if len(t.split()[0]) <= 0.2 * len(t)]
    assert len(items) > 20
    assert recall(items, lambda r, t: " ".join(["q" * len(t.split()[0]), *t.split()[1:]])) == 1


def edited(r, text, share):
    out = list(text)
    for at in sorted(r.sample(range(len(out)), int(share * len(out))), reverse=True):
        kind = r.random()
        out[at : at + 1] = [r.choice(LETTERS)] if kind < 0.6 else [] if kind < 0.8 else [r.choice(LETTERS), out[at]]
    return "".join(out)


@pytest.mark.parametrize("n_words", [5, 8, 15, 20, 40, 58, 150])
@pytest.mark.parametrize("share", [0.05, 0.1, 0.15, 0.19])
def test_items_with_scattered_wrong_letters(n_words, share):
    """Target recall: 0.99 up to 15 % of the letters, 0.95 just within the similarity."""
    assert recall(items_of(n_words), lambda r, t: edited(r, t, share)) >= (0.99 if share <= 0.15 else 0.95)


def test_items_without_spaces():
    r = random.Random(3)
    items = [(k, "".join(chr(r.randrange(0x4E00, 0x5200)) for _ in range(60))) for k in range(40)]
    assert recall(items, lambda r, t: t[:20] + "x" + t[23:]) == 1


def test_short_items_match_their_exact_words():
    index = decontaminate.ItemIndex.build([(1, "two words"), (2, "Alone"), (3, "one two three four"), (4, "two words"), (5, " .")])
    texts = ["x two Words y", "two wordss", "alone", "zero one two three four", "one two three", "", None or ""]
    assert [{index.ids[i]: v for i, v in f.items()} for f in index.matches(texts, 0.8)] == [{1: (0, 1), 4: (0, 1)}, {}, {2: (0, 0)}, {3: (0, 1)}, {}, {}, {}]


@pytest.mark.parametrize("n_words", [5, 12, 30, 80])
@pytest.mark.parametrize("share", [0.02, 0.04, 0.06, 0.08, 0.1, 0.12, 0.15, 0.2])
def test_recall_by_character_edits(n_words, share):
    """Target 0.9 at every rate, counted over the edited items that the exact distance accepts."""
    r = random.Random(n_words)
    items = items_of(n_words, 200)
    index = decontaminate.ItemIndex.build(items)
    changed = [edited(r, t, share) for _, t in items]
    near = [k for k, (_, t) in enumerate(items) if decontaminate.edit_distance_within(t, changed[k])[0] <= int(0.2 * len(t) + 1e-9)]
    found = index.matches([f"some filler {changed[k]} more words" for k in near], decontaminate.SIMILARITY)
    assert len(near) > 50
    assert np.mean([k in {index.ids[i] for i in f} for k, f in zip(near, found, strict=True)]) >= 0.9


def test_against_every_window_of_every_document(spark):
    """Brute force on the smallest tables: the exact distance of every item to every document."""
    sf = "/root/testdata/sf0.001"
    docs, items = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/benchmark.parquet")
    plain = lambda t: b" ".join(decontaminate.words_of(t or "")).decode("utf-8", "replace")
    known = {r.item_id: plain(r.text) for r in items.collect()}
    masks = {i: decontaminate.row_masks(t) for i, t in known.items()}
    want = {}
    for r in docs.collect():
        text = plain(r.text)
        width = {i: m[1].shape[1] for i, m in masks.items()}
        for w in set(width.values()):
            own = [i for i in known if width[i] == w]
            step = 4 * 64 * w
            blocks = [text[a : a + 2 * step] for a in range(0, max(len(text), 1), step)]  # every stretch of an item's length lies in a block
            for i, (distance, _) in zip([i for i in own for _ in blocks], decontaminate.edit_distances([(known[i], masks[i], b) for i in own for b in blocks]), strict=True):
                if distance <= int(0.2 * len(known[i]) + 1e-9):
                    want[r.doc_id, i] = min(distance, want.get((r.doc_id, i), distance))
    got = {(r.doc_id, r.item_id): r.edit_distance for r in decontaminate.leaks(docs, items).collect()}
    assert got == want and want


def test_distances_of_many_pairs_at_once():
    r = random.Random(8)
    for words in (1, 2, 3):
        pairs = []
        for _ in range(200):
            item = "".join(r.choice("abcd ") for _ in range(r.randrange(64 * (words - 1) + 1, 64 * words + 1)))
            text = "".join(r.choice("abcde ") for _ in range(r.randrange(150)))
            pairs.append((item, decontaminate.row_masks(item), text[:40] + item[: r.randrange(len(item))] + text[40:] if r.random() < 0.5 else text))
        assert decontaminate.edit_distances(pairs) == [decontaminate.edit_distance_within(a, b) for a, _, b in pairs]

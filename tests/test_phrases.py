"""Phrase queries without a cap on length against brute force on a small table."""

from collections import Counter

import pytest
from pyspark.sql import functions as F

from momenttree.operators import phrases as P
from momenttree.queries import QUERIES, load

load()
LONG = "red green blue black white brown"


@pytest.fixture(scope="module")
def small(spark, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("small"))
    texts = [LONG] * 45 + ["red green"] * 50 + ["pale sky"] * 3
    rows = [(k, t + ".", ("en", "fr")[k % 2], "s", len(t) + 1) for k, t in enumerate(texts)]
    spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint").write.parquet(f"{path}/documents.parquet")
    grams = lambda w: [" ".join(w[i : i + n]) for n in range(1, len(w) + 1) for i in range(len(w) - n + 1)]
    return path, [grams(t.split()) for t in texts]


def test_phrases_of_any_length(spark, small):
    path, grams = small
    want = {p: c for p, c in Counter(p for g in grams for p in g).items() if c >= 40}
    run = lambda name: QUERIES[name](spark, path).collect()
    assert {r.phrase: r.support for r in run("frequent_phrases_whole")} == want and LONG in want
    assert {r.phrase for r in run("complete_phrases_whole")} == {LONG, "red green"}
    assert {r.phrase for r in run("phraseness_whole")} == {p for p in want if " " in p}
    assert {(r.doc_id, r.phrase, r.c) for r in run("phrase_counts_whole")} == {(k, p, c) for k, g in enumerate(grams) for p, c in Counter(g).items() if p in want}


def test_only_complete_and_significant_phrases_are_ranked(spark, small):
    path, grams = small
    counts = QUERIES["topical_phrase_counts_whole"](spark, path).where("path = 'o'").collect()
    assert {(r.doc_id, r.phrase, r.c) for r in counts} == {(k, p, float(c)) for k, g in enumerate(grams) for p, c in Counter(g).items() if p in (LONG, "red green")}
    assert {r.phrase for r in QUERIES["phrase_ranking_whole"](spark, path).collect()} == {LONG, "red green"}
    assert {r.phrase for r in QUERIES["plural_collapsed_whole"](spark, path).collect()} == {LONG, "red green"}
    chance = spark.createDataFrame([("a", 1, 900), ("b", 1, 900), ("c", 1, 60), ("d", 1, 60), ("a b", 2, 50), ("c d", 2, 50)], "phrase string, n int, support bigint")
    assert {r.phrase for r in P.quality(chance, 10_000).collect()} == {"a", "b", "c", "d", "c d"}


def test_long_phrases_take_few_rounds(spark):
    """Runs of 150 words in near copies, found in stretches of twice the length each round; brute force beside."""
    line = [f"{chr(97 + k % 26)}{chr(97 + k // 26)}" for k in range(150)]
    texts = [line] * 2 + [line[:70] + ["other"] + line[71:]] * 2 + [line[90:]] + [["x", "y"] * 20]
    rows = spark.createDataFrame([(k, 0, t) for k, t in enumerate(texts)], "doc_id bigint, sent_no int, words array<string>")
    want = Counter(" ".join(t[i : i + n]) for t in texts for n in range(1, len(t) + 1) for i in range(len(t) - n + 1))
    for most in (None, 7):
        by_doc = rows.selectExpr("cast(doc_id AS bigint) AS doc_id", "array(words) AS sents")
        got, by_rows = ({r.phrase: (r.n, r.support) for r in df.collect()} for df in (P.mine(by_doc, 3, most).phrases, P.mine_phrases(rows, 3, most)))
        assert got == by_rows == {p: (p.count(" ") + 1, c) for p, c in want.items() if c >= 3 and (most is None or p.count(" ") < most)}


def test_counts_and_probabilities_in_place(spark):
    """The same as by exploded rows; rows of one doc_id count together, rows without one in no document's sum."""
    docs = spark.createDataFrame([(1, "a b c. a b"), (1, "b c\na"), (2, None), (3, ""), (4, "c a b c!"), (None, "a b"), (5, "d")], "doc_id bigint, text string")
    by_doc = P.by_document(docs)
    mined = P.mine(by_doc, 2)
    some = mined.phrases.where("phrase <> 'b'")
    rows = lambda df: {tuple(r) for r in df.collect()}
    counts = P.phrase_counts(P.sentences_of(by_doc), some, 3)
    assert rows(P.counts_in_place(mined, some)) == rows(counts)
    assert (1, "a", 3) in rows(counts) and (1, "b c", 2) in rows(counts)
    shares = spark.createDataFrame([("a", "o/1", 0.25), ("a", "o/2", 0.75), ("a b", "o/1", 1.0)], "phrase string, path string, share double")
    own = counts.where("doc_id is not null")
    want = P.phrase_probability(own.selectExpr("doc_id", "'o' AS path", "phrase", "double(c) AS c").union(own.join(shares, "phrase").selectExpr("doc_id", "path", "phrase", "c * share")), 6)
    got = P.probability_in_place(mined, some, shares, 6)
    assert {(r.path, r.phrase): round(r.p, 9) for r in got.collect()} == {(r.path, r.phrase): round(r.p, 9) for r in want.collect()}


def test_measures_of_mined_phrases(spark):
    """ratio and z by numbers are those by rows."""
    texts = ["a b c d e f"] * 5 + ["a b c"] * 4 + ["c d", "a c", "b d a b"] * 3
    by_doc = P.by_document(spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string"))
    mined, n = P.mine(by_doc, 2), P.n_tokens_of(by_doc)
    rows = mined.phrases.collect()
    assert {r.phrase: round(r.ratio, 9) for r in rows} == {r.phrase: round(r.ratio, 9) for r in P.complete_ratio(mined.phrases.select("phrase", "n", "support")).collect()}
    assert {r.phrase: round(r.z, 9) for r in rows if r.n > 1} == {r.phrase: round(r.z, 9) for r in P.phraseness(mined.phrases.select("phrase", "n", "support"), n).collect()}


def test_words_of_phrases_are_written_where_they_are_wanted(spark):
    """85M words in 320,400 phrases: still by numbers, and only the phrases asked for are spelled."""
    line = [f"{chr(97 + k % 26)}{chr(97 + k // 26 % 26)}{chr(97 + k // 676)}" for k in range(800)]
    by_doc = P.by_document(spark.createDataFrame([(k, " ".join(line)) for k in range(2)], "doc_id bigint, text string"))
    mined = P.mine(by_doc, 2)
    assert mined.codes is not None and mined.size == mined.measures.where("support = 2").count() == 800 * 801 // 2
    for n in (1, 2, 513, 799, 800):
        assert {r.phrase for r in mined.where(f"n = {n}").collect()} == {" ".join(line[i : i + n]) for i in range(801 - n)}
    assert {r.phrase for r in mined.where("ratio < 1").collect()} == {" ".join(line)}
    assert {(r.doc_id, r.phrase, r.c) for r in P.counts_in_place(mined, mined.where("n = 799")).collect()} == {(k, " ".join(line[i : i + 799]), 1) for k in range(2) for i in range(2)}


def test_posterior_rows_carry_ids_of_long_phrases(spark):
    """Shares are the same by ids as by texts; with ids, no row of a word holds its phrase."""
    nodes = spark.createDataFrame([("o/1", "o", 0.75), ("o/2", "o", 0.25)], "path string, parent string, alpha double")
    words = spark.createDataFrame([("o/1", "a", 0.5), ("o/1", "b", 0.5), ("o/2", "a", 1.0)], "path string, term string, phi double")
    phrases = spark.createDataFrame([(7, "a"), (8, "a b"), (9, "a a"), (10, "c")], "id int, phrase string")
    shares = P.phrase_posterior(phrases, words, nodes)
    got, by_text = ({(r.phrase, r.path): round(r.share, 9) for r in df.collect()} for df in (shares, P.phrase_posterior(phrases.select("phrase"), words, nodes)))
    assert got == by_text == {("a", "o/1"): 0.6, ("a", "o/2"): 0.4, ("a b", "o/1"): 1.0, ("a a", "o/1"): 0.428571429, ("a a", "o/2"): 0.571428571}
    generated = [line for line in shares._jdf.queryExecution().optimizedPlan().toString().splitlines() if "Aggregate" in line]
    assert generated and not any("phrase#" in line for line in generated)


def test_phrases_without_probability_come_last(spark):
    """A share too small for a double leaves a parent's p at 0, too."""
    rows = [("o", "a", 0.5), ("o", "b", 0.5), ("o/1", "a", 0.9), ("o/1", "b", 0.0), ("o/1/1", "b", 0.0), ("o/1/1", "a", 0.2)]
    probability = spark.createDataFrame(rows, "path string, phrase string, p double")
    for by in ("both", "ratio", "popularity"):
        got = {(r.path, r["rank"], r.phrase, r.p_topic, r.score is None) for r in P.rank_phrases(probability, by=by).collect()}
        assert got == {(path, k, w, p, by != "popularity" and w == "b") for path, k, w, p in [("o/1", 1, "a", 0.9), ("o/1", 2, "b", 0.0), ("o/1/1", 1, "a", 0.2), ("o/1/1", 2, "b", 0.0)]}


def test_counts_of_pairs_and_sums_of_shares_travel_in_arrays(spark, monkeypatch):
    """No row of a shuffle is one pair, or one phrase and node, of one task; groups of nodes in further scans give the same."""
    import numpy as np

    for x in (np.array([5, 0, -3, 1 << 61]), np.array([0.1, -2.0, 0.0])):
        assert (P._unpacked(P._packed(x), len(x), x.dtype.type) == x).all()
    texts = ["a b c d a b", "b c d", "a b", "c d a"] * 5
    by_doc = P.by_document(spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string").repartition(7))
    made = []
    monkeypatch.setattr(P, "cut", lambda df, f=P.cut: made.append(df) or f(df))
    mined = P.mine(by_doc, 5)
    plans = [df._jdf.queryExecution().optimizedPlan().toString() for df in made]
    assert any("RepartitionById" in p or "RepartitionByExpression" in p for p in plans) and not any("Aggregate [d#" in p for p in plans)
    shares = spark.createDataFrame([(p, f"o/{k}", w) for p in ("a", "a b", "c d") for k, w in ((1, 0.25), (2, 0.75))], "phrase string, path string, share double")
    got = []
    for most, scans in ((4_000_000, 16), (3, 16), (3, 1)):  # one scan, one for each node, by rows
        monkeypatch.setattr(P, "SHARES_SENT", most)
        monkeypatch.setattr(P, "SCANS", scans)
        df = P.probability_in_place(mined, mined.phrases, shares, 20)
        got.append({(r.path, r.phrase): round(r.p, 12) for r in df.collect()})
    assert got[0] == got[1] == got[2] and got[0]["o/1", "a"] > 0


def test_words_are_counted_by_tag_where_documents_are(spark):
    """Rows of one doc_id with several tags count for each; null tags and ids for none.  No counts of documents are shuffled."""
    docs = spark.createDataFrame([(1, "a b. a", "x"), (1, "b", "y"), (2, "a a", "x"), (3, "b b", None), (None, "a", "x"), (4, "", "y"), (5, None, "y")], "doc_id bigint, text string, t string")
    want = {("x", "a"): 4, ("x", "b"): 2, ("y", "a"): 2, ("y", "b"): 2}
    by_doc = P.by_document(docs, F.col("t"))
    mined = P.mine(by_doc, 2)
    by_rows = P.Mined(by_doc, P.mine_phrases(P.sentences_of(by_doc), 2))
    for m in (mined, by_rows):
        assert {(r.tag, r.term): r.c for r in P.words_by_tag(m).collect()} == want
    assert P.words_by_tag(P.mine(by_doc, 100)).count() == 0

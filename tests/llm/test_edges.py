"""Every operator on nulls, empty and very long texts, ties, repeated rows, empty tables and clashing extra columns."""

import pytest
from pyspark.sql import functions as F

from momenttree.llm import bpe, decontaminate, labelled, licences, minhash, quality, secrets, simhash, token_counts, toxicity, urls

DDL = "doc_id bigint, text string, lang string, source string, n_chars bigint"
LONG = "the quick brown fox " * 30_000
ROWS = [
    (1, "one two three four five six seven", "en", "a", 33),
    (1, "one two three four five six seven", "en", "a", 33),
    (2, None, None, None, None),
    (3, "", "en", "a", 0),
    (4, LONG, "en", "b", len(LONG)),
    (5, "one two three four five six seven", "en", "b", 33),
    (None, "password = abcdef123456789", "en", "c", 26),
    (6, "x" * 200_000, "en", "b", 200_000),
    (7, " \n\t ", "en", "b", 4),
    (8, "naïve 😀 text\n\nwith   lines <|endoftext|> end", "fr", "b", 44),
]
CLASH = "row fp component component_id owner repository base opaque scanned ids n_tokens score edge edge_id key half form own allowed path lines license share y h n value live variant".split()


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, DDL).withColumns({c: F.lit("clash") for c in CLASH})


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DDL)


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(1, 1, 0), (1, 1, 0), (4, 0, 1), (5, 1, None), (None, 1, 1), (8, 0, 0), (9, 1, 1)], "doc_id bigint, quality int, toxic int").withColumn("y", F.lit("clash"))


@pytest.fixture(scope="module")
def items(spark):
    return spark.createDataFrame([(1, "one two three four five six seven"), (1, "one two three four five six seven"), (2, None), (None, "a b c d e f"), (3, "")], "item_id bigint, text string")


OPERATORS = {
    "bpe": lambda d, labels, items: bpe.digests(d),
    "tokens": lambda d, labels, items: token_counts.count(d),
    "toxicity": lambda d, labels, items: toxicity.judge(d, labels),
    "licences": lambda d, labels, items: licences.scan(d),
    "quality": lambda d, labels, items: quality.judge(d, labels),
    "simhash": lambda d, labels, items: simhash.classes(d),
    "secrets": lambda d, labels, items: secrets.report(d),
    "minhash": lambda d, labels, items: minhash.with_edited(d),
    "near_classes": lambda d, labels, items: minhash.near_classes(d),
}


@pytest.mark.parametrize("name", OPERATORS)
def test_one_row_for_each_document(name, docs, none, labels, items):
    got = OPERATORS[name](docs, labels, items)
    rows = got.collect()
    if name == "tokens":
        assert {r.doc_id for r in rows} == {r[0] for r in ROWS}
    else:
        assert sorted((r.doc_id is not None, r.doc_id or 0) for r in rows) == sorted((r[0] is not None, r[0] or 0) for r in ROWS)
    assert OPERATORS[name](none, labels, items).collect() == []


def test_equal_rows_are_treated_alike(docs, labels, items):
    for name in ("bpe", "toxicity", "quality", "simhash", "licences", "secrets", "near_classes"):
        rows = [tuple(r) for r in OPERATORS[name](docs, labels, items).collect() if r.doc_id == 1]
        assert len(rows) == 2 and rows[0] == rows[1], name


def test_models_without_labels(docs, labels):
    empty = labels.limit(0)
    assert {r.score for r in quality.judge(docs, empty).collect()} == {0.5}
    assert {r.score for r in toxicity.judge(docs, empty).collect()} == {0.0}
    assert quality.keep_good(docs, empty).count() == len(ROWS)


def test_decontamination(docs, none, items):
    found = decontaminate.leaks(docs, items)
    assert {(r.doc_id, r.item_id, r.edit_distance) for r in found.collect()} == {(1, 1, 0), (5, 1, 0)}
    kept = decontaminate.drop_leaks(docs, items)
    assert kept.columns == docs.columns
    assert kept.count() == len(ROWS) - 3
    assert decontaminate.leaks(none, items).count() == 0
    assert decontaminate.leaks(docs, items.limit(0)).count() == 0
    assert decontaminate.drop_leaks(docs, items.limit(0)).count() == len(ROWS)


def test_stages_keep_columns(docs, none, spark):
    for stage in (simhash.keep_one, secrets.redact):
        assert stage(docs).columns == docs.columns
        assert stage(none).collect() == []
    kept = sorted(r.doc_id or 0 for r in simhash.keep_one(docs).select("doc_id").collect())
    # 2, 3 and 7 have no word: fingerprint zero, one class; 1 and 5 are equal; the row without an id stays
    assert kept == [0, 1, 2, 4, 6, 8]
    assert [r.text for r in secrets.redact(docs).where("doc_id is null").collect()] == ["[secret]"]


def test_rows_of_one_id_and_different_texts(spark):
    """Each text's class keeps its own row; the choice does not depend on the order of rows."""
    rows = [(1, "one two three four five", "en", "a", 1), (1, "six seven eight nine ten", "en", "a", 2), (2, "one two three four five", "en", "a", 3), (1, "one two three four five", "en", "a", 4)]
    for order in (rows, rows[::-1]):
        kept = simhash.keep_one(spark.createDataFrame(order, DDL).repartition(3))
        assert sorted(tuple(r) for r in kept.collect()) == sorted([rows[0], rows[1]])
        taught = labelled.sample(spark.createDataFrame(order, DDL), spark.createDataFrame([(1, 1)], "doc_id bigint, quality int"), "quality", F.lit(True), 10)
        assert [(r.doc_id, r.text, r.y) for r in taught.collect()] == [(1, rows[0][1], 1)]
        assert sorted(tuple(r) for r in minhash.near_classes(spark.createDataFrame(order, DDL)).collect()) == [(1, 1), (1, 1), (1, 1), (2, 1)]


def test_urls(spark):
    rows = [(1, "http://A.example.org/en/1?x", None), (1, "http://A.example.org/en/1?x", None), (2, None, "<html>"), (3, "no scheme", ""), (None, "ftp://com", None), (4, "http://x.com/de/", "<link rel=canonical href='http://y.net/z'>"), (5, "https://www.y.net/z/", None), (6, "http://q.net/", None)]
    pages = spark.createDataFrame(rows, "page_id bigint, url string, html string").withColumns({c: F.lit("clash") for c in CLASH + ["host", "rule", "verdict"]})
    got = {r.page_id: r for r in urls.judge(pages).collect()}
    assert urls.judge(pages).count() == len(rows)
    assert (got[1].host, got[1].path, got[1].rule, got[1].verdict) == ("a.example.org", "/en/1", "example.org/en/1", "block")
    assert (got[2].host, got[2].path, got[2].rule, got[2].verdict) == ("", "", None, "allow")
    assert (got[3].host, got[3].path) == ("", "")
    assert (got[None].host, got[None].path, got[None].rule) == ("com", "", None)
    assert got[4].verdict == "block"
    assert (got[5].verdict, got[5].decided_by) == ("block", "alias")
    assert (got[6].verdict, got[6].decided_by) == ("allow", "default")
    assert urls.judge(pages.limit(0)).collect() == []
    more = spark.createDataFrame([("http://y.net/z", "http://any.org/ok"), ("http://any.org/ok", "http://q.net")], "a string, b string")
    seen = spark.createDataFrame([*rows, (7, "http://any.org/ok", None)], "page_id bigint, url string, html string")
    linked = {r.page_id: r for r in urls.judge(seen, links=more).collect()}
    assert linked[5].verdict == "allow" and linked[6].verdict == "allow" and linked[4].verdict == "block"
    with pytest.raises(ValueError):
        urls.judge(pages, [("h", "/", "allow")] * (urls.RULES_MOST + 1))

"""The experiments run and show what they should on the smallest tables."""

import pytest

from momenttree.workloads import experiments as E

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def abstracts(spark):
    return E.prepare(spark, SF, "abstracts", top=150, stop=False)


def test_corpora(spark, abstracts):
    assert abstracts.n_docs > 50 and abstracts.v == 150
    assert {n: E.CORPORA[n](spark, SF).columns[:2] for n in E.CORPORA} == dict.fromkeys(E.CORPORA, ["doc_id", "text"])
    stemmed = E.prepare(spark, SF, "everything", top=150)
    assert stemmed.n_docs > abstracts.n_docs


def test_scans_do_not_grow_with_width_or_documents(abstracts):
    assert {r["scans"] for r in E.sweep(abstracts, "width", [2, 3], height=2)} == {4}
    assert {r["scans"] for r in E.sweep(abstracts, "fraction", [0.5, 1.0], height=1)} == {2}
    assert [r["scans"] for r in E.sweep(abstracts, "height", [1, 2], width=2)] == [2, 4]


def test_more_steps_less_variance(abstracts):
    rows = {(r["factor"], r["value"]): r["variance"] for r in E.iteration_sweep(abstracts, values=(1, 20), runs=2, width=3)}
    assert rows["steps", 20] <= rows["steps", 1] and rows["steps", 20] < 0.01


def test_dense_variants_stop_at_large_vocabularies(spark):
    rows = {(r["words"], r["variant"]): r["stopped"] for r in E.vocab_sweep(spark, SF, sizes=(40, 400), variants=("lean", "dense"), width=3)}
    assert rows[40, "dense"] is None and rows[400, "dense"] == "VocabularyTooLarge" and rows[400, "lean"] is None


def test_phrases_of_a_tree(spark, abstracts):
    tree = E.methods(3, 2)["lean"](abstracts)
    ranked = E.ranked_phrases(spark, SF, abstracts, tree, min_support=10, max_len=2)
    assert set(ranked) <= set(tree.nodes) - {"o"} and any(p.count("/") == 2 for p in ranked)
    assert all(len(set(x)) == len(x) <= 10 for x in ranked.values())
    assert E.as_table(spark, [{"a": 1, "b": 2.0}]).count() == 1


def test_entry_and_catalogue(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).columns == ["path", "rank", "term", "phi"] and entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())

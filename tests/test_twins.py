"""Queries whose rows have to be those of their DuckDB twins, on the smallest tables."""

import pytest
from compare import compare
from pyspark.errors import AnalysisException

from momenttree.queries import ORACLES, QUERIES, load

load()
SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["topic_cube", "topic_rollup", "topic_grouping_sets", "topic_pivot"])
def test_hard_topics(spark, name):
    assert compare(spark, name, QUERIES[name], ORACLES[name], SF).startswith("equal")


def test_divergence_by_pandas_udf(spark):
    assert compare(spark, "udf_kl", QUERIES["udf_kl"], ORACLES["udf_kl"], SF).startswith("equal")


MOVED = ["exact_recovery", "collapse_prune", "topic_matching", "intrusion_questions", "intrusion_f1", "corpus_source_rows", "baseline_nested_partition", "sql_surface"]


@pytest.mark.parametrize("name", MOVED)
def test_moved_onto_given_tables(spark, name):
    """The rows are those of the twin, and without tables there are none."""
    assert compare(spark, name, QUERIES[name], ORACLES[name], SF).startswith("equal")
    with pytest.raises(AnalysisException):
        QUERIES[name](spark, "/tmp/no_such_tables").collect()

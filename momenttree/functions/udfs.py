"""User-defined functions and their registration for SQL."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F



def kl_divergence():
    """Scalar pandas UDF: divergence of the first array from the second, smoothed by 1e-12."""

    @F.pandas_udf("double")
    def run(p: pd.Series, q: pd.Series) -> pd.Series:
        def one(a, b):
            if a is None or b is None:
                return None
            a, b = np.asarray(a, float) + 1e-12, np.asarray(b, float) + 1e-12
            a, b = a / a.sum(), b / b.sum()
            return float((a * np.log(a / b)).sum())

        return pd.Series([one(a, b) for a, b in zip(p, q, strict=True)])

    return run


def vector_sum():
    """Grouped aggregate pandas UDF: element-wise sum of equally long arrays."""

    @F.pandas_udf("array<double>")
    def run(v: pd.Series) -> list:
        rows = [np.asarray(x, float) for x in v if x is not None]
        return np.sum(rows, axis=0).tolist() if rows else []

    return run


class Ngrams:
    """Table function: pos, n, gram of all runs of n_min to n_max tokens."""

    def eval(self, tokens: list, n_min: int, n_max: int) -> Iterator[tuple[int, int, str]]:
        for n in range(n_min, n_max + 1):
            for i in range(len(tokens or []) - n + 1):
                yield i, n, " ".join(tokens[i : i + n])


class Ancestors:
    """Table function: level, ancestor of a path, from the root to the path itself."""

    def eval(self, path: str) -> Iterator[tuple[int, str]]:
        parts = path.split("/") if path else []
        for k in range(len(parts)):
            yield k, "/".join(parts[: k + 1])


def ngrams():
    return F.udtf(Ngrams, returnType="pos int, n int, gram string")


def ancestors():
    return F.udtf(Ancestors, returnType="level int, ancestor string")


def sparse_dot(terms, counts, weights):
    """Dot product of a sparse bag with a dense array column, in column functions."""
    return F.aggregate(F.zip_with(terms, counts, lambda t, c: c * F.coalesce(F.get(weights, t), F.lit(0.0))), F.lit(0.0), lambda a, x: a + x)


def register(spark: SparkSession, views: dict[str, DataFrame] | None = None) -> None:
    """SQL names: kl_divergence, vector_sum, ngrams, ancestors, topic_level, topic_parent; and views such as topic_node."""
    spark.udf.register("kl_divergence", kl_divergence())
    spark.udf.register("vector_sum", vector_sum())
    spark.udtf.register("ngrams", ngrams())
    spark.udtf.register("ancestors", ancestors())
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION topic_level(p STRING) RETURNS INT RETURN length(p) - length(replace(p, '/', ''))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION topic_parent(p STRING) RETURNS STRING RETURN CASE WHEN contains(p, '/') THEN regexp_replace(p, '/[^/]*$', '') END")
    for name, view in (views or {}).items():
        view.createOrReplaceTempView(name)

"""Documents to topics by the trees' word posteriors."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from momenttree.operators.tree import TopicTree
from momenttree.plans.build import word_weights


def weights_df(spark: SparkSession, tree: TopicTree, least: float = 1e-6) -> DataFrame:
    """path, term_id, omega of every node but the root; bounded by vocabulary times nodes."""
    own = {p: (np.flatnonzero(w > least), w) for p, w in word_weights(tree).items() if w is not None}
    names = pa.array([p for p, (x, _) in own.items() for _ in x], pa.string())
    terms = pa.array(np.concatenate([np.zeros(0, np.int32), *(x.astype(np.int32) for x, _ in own.values())]))
    omega = pa.array(np.concatenate([np.zeros(0), *(w[x] for x, w in own.values())]))
    return spark.createDataFrame(pa.table([names, terms, omega], ["path", "term_id", "omega"]))


def topical_counts(long_bags: DataFrame, weights: DataFrame) -> DataFrame:
    """doc_id, path, len_t: the expected number of a document's tokens of each topic."""
    return long_bags.join(F.broadcast(weights), "term_id").groupBy("doc_id", "path").agg(F.sum(F.col("c") * F.col("omega")).alias("len_t"))


def assign(long_bags: DataFrame, weights: DataFrame, level: int = 1, mode: str = "soft") -> DataFrame:
    """doc_id, path, theta at one level; hard keeps the largest (the first path of equals)."""
    from momenttree.functions import paths

    counts = topical_counts(long_bags, weights.where(paths.level(F.col("path")) == level))
    theta = counts.withColumn("theta", F.col("len_t") / F.sum("len_t").over(Window.partitionBy("doc_id"))).select("doc_id", "path", "theta")
    if mode == "soft":
        return theta
    best = theta.groupBy("doc_id").agg(F.min(F.struct((-F.col("theta")).alias("order"), "path")).alias("b"))
    return best.select("doc_id", F.col("b.path").alias("path"), (-F.col("b.order")).alias("theta"))

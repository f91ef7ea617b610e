"""Connected components by randomised contraction, in DataFrame operations only.

In each round every vertex is renamed to the member of its closed neighbourhood with the smallest hash of that
round, links follow, loops and repeats vanish.  The number of vertices falls by a constant factor in expectation
for any shape of graph, so long chains need no more rounds than stars.  A hub is a sum over its links (partial
aggregation) and a join whose other side has unique keys (which adaptive execution splits); no neighbourhood is
ever gathered.  Each round ends in a checkpoint.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from momenttree.llm.runtime import cut, ship


def _renaming(links: DataFrame, round_no: int) -> DataFrame:
    order = lambda c: F.struct(F.xxhash64(F.col(c), F.lit(round_no)).alias("h"), F.col(c).alias("id"))
    both = links.select("a", "b").union(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
    return both.groupBy("a").agg(F.min(order("b")).alias("best")).select(F.col("a").alias("old"), F.least("best", order("a"))["id"].alias("new"))


#: Links that one task may join, about 100 MB of names.
IN_TASK = 300_000


def _joined_in_task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(old, new) of every vertex of the links, by union-find."""
    up: dict = {}

    def top(x):
        while (above := up.setdefault(x, x)) != x:
            up[x] = x = up.setdefault(above, above)
        return x

    kind = None
    for batch in batches:
        kind = batch.column(0).type
        for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            up[top(a)] = top(b)
    if up:
        yield pa.RecordBatch.from_arrays([pa.array(list(up), kind), pa.array([top(x) for x in list(up)], kind)], ["old", "new"])


def components(links: DataFrame, in_task: int = 0) -> DataFrame:
    """id, component (the smallest id reached) for every id that occurs in links (columns a, b of one orderable type).

    Null ends are ignored; loops make their id a component of its own; repeated links count once.  As soon as at most
    in_task links are left, one task joins them: every round costs the driver the plans of several jobs.
    """
    links = links.where("a is not null and b is not null")
    ids = links.select(F.col("a").alias("id")).union(links.select(F.col("b").alias("id"))).distinct()
    names = ids.select("id", F.col("id").alias("name"))
    left = cut(links.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct())
    round_no = 0
    while not left.isEmpty():
        if in_task and left.count() <= in_task:
            ship(left.sparkSession)
            kind = left.schema["a"].dataType.simpleString()
            renaming = left.select("a", "b").coalesce(1).mapInArrow(_joined_in_task, f"old {kind}, new {kind}")
            names = cut(names.join(renaming, F.col("name") == F.col("old"), "left").select("id", F.coalesce("new", "name").alias("name")))
            break
        renaming = cut(_renaming(left, round_no))
        names = cut(names.join(renaming, F.col("name") == F.col("old"), "left").select("id", F.coalesce("new", "name").alias("name")))
        to_a, to_b = renaming.toDF("a", "new_a"), renaming.toDF("b", "new_b")
        left = left.join(to_a, "a").join(to_b, "b").where("new_a <> new_b")
        left = cut(left.select(F.least("new_a", "new_b").alias("a"), F.greatest("new_a", "new_b").alias("b")).distinct())
        round_no += 1
    smallest = names.groupBy("name").agg(F.min("id").alias("component"))
    return names.join(smallest, "name").select("id", "component")

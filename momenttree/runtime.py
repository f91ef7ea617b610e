"""Shared pieces: sending the package to executors, shared storage, cutting lineage."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile

from pyspark.sql import DataFrame, SparkSession

_SHIPPED: dict[str, str] = {}


def ship(spark: SparkSession) -> None:
    """Give the executors this package once for each application, as a zip through Spark's own file server."""
    app = spark.sparkContext.applicationId
    if app in _SHIPPED:
        return
    package = os.path.dirname(os.path.abspath(__file__))
    _SHIPPED[app] = package
    if not os.path.isdir(package):  # already inside a zip that a cluster manager has sent
        return
    path = os.path.join(tempfile.mkdtemp(), "momenttree_core.zip")
    with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as out:
        for folder, _, names in os.walk(package):
            for name in names:
                if name.endswith(".py"):
                    full = os.path.join(folder, name)
                    out.write(full, os.path.relpath(full, os.path.dirname(package)))
    spark.sparkContext.addPyFile(path)


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the cluster; a temporary folder where it is unset and the master is local (tests)."""
    set_to = spark.conf.get("spark.checkpoint.dir", None)
    context = spark.sparkContext
    if context._jsc.sc().getCheckpointDir().isEmpty():
        if not set_to and not context.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir has to name a folder that driver and executors share")
        context.setCheckpointDir(set_to or tempfile.mkdtemp(prefix="momenttree_checkpoint_"))
    return set_to or context._jsc.sc().getCheckpointDir().get()


def cut(df: DataFrame) -> DataFrame:
    """Rows of df from reliable shared storage; its lineage ends here."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def stored(df: DataFrame, name: str) -> DataFrame:
    """df written as Parquet in the shared folder under a fresh name and read again."""
    path = f"{shared_dir(df.sparkSession).rstrip('/')}/{name}_{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def group_nodes(names: list[str], bytes_each: int, most: int) -> list[list[str]]:
    """names in groups whose arrays together take at most `most` bytes (one name at least)."""
    n = max(1, int(most // max(bytes_each, 1)))
    return [names[at : at + n] for at in range(0, len(names), n)]


#: Set to true by the bench alone: tables are dealt to all cores before use, since its tables are single files of one row group.
SPREAD = "spark.momenttree.spread"


def spread(df: DataFrame) -> DataFrame:
    """df as it is; dealt to all cores where the session asks for it (SPREAD), whatever its size."""
    spark = df.sparkSession
    return df.repartition(spark.sparkContext.defaultParallelism) if spark.conf.get(SPREAD, "false") == "true" else df

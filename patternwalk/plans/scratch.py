"""Cut points of long plans: a Parquet table in the folder that the cluster shares.

A cut table outlives the executors that wrote it, so a lost executor costs only
the tasks it was running, and a loop's plan stays as short as one round. Who cuts
drops: operators delete a cut table once its successor is written.
"""

from __future__ import annotations

import contextlib
import tempfile
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession

#: While it is set, Spark deletes a query's shuffle files when the query ends.
_TIDY = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_OWN: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; a local one only where none is set and all runs in one process."""
    if named := spark.conf.get("spark.checkpoint.dir", None):
        return named.rstrip("/")
    held = spark.sparkContext._jsc.sc().getCheckpointDir()
    if held.isDefined():
        return str(held.get()).rstrip("/")
    if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
        raise ValueError("on a cluster spark.checkpoint.dir must name a shared folder")
    app = spark.sparkContext.applicationId
    if app not in _OWN:
        _OWN[app] = tempfile.mkdtemp(prefix="patternwalk-")
    return _OWN[app]


@contextlib.contextmanager
def tidy(spark: SparkSession) -> Iterator[None]:
    """Queries that run in here leave no shuffle files behind."""
    before = spark.conf.get(_TIDY, None)
    spark.conf.set(_TIDY, "true")
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(_TIDY)
        else:
            spark.conf.set(_TIDY, before)


def cut(df: DataFrame, name: str, partition_by: list[str] | None = None, hashes: bool = False) -> DataFrame:
    """Write ``df`` once and go on from the written rows. ``hashes``: most columns are, so dictionaries of them would be built for nothing."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/cut-{name}-{uuid.uuid4().hex}"
    writer = df.write
    if hashes:
        writer = writer.option("parquet.enable.dictionary", "false")
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    with tidy(spark):
        writer.parquet(path)
    held = spark.read.schema(df.schema).parquet(path)
    held.cut_path = path
    return held


def drop(*frames: DataFrame) -> None:
    """Delete cut tables that nothing reads any more: frames as :func:`cut` gave them."""
    for df in frames:
        spark = df.sparkSession
        where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(df.cut_path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def sweep(spark: SparkSession) -> None:
    """Delete every cut table of this folder; call it when no frame that reads one is needed any more."""
    jvm = spark.sparkContext._jvm
    root = jvm.org.apache.hadoop.fs.Path(shared_dir(spark))
    fs = root.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    if fs.exists(root):
        for entry in fs.listStatus(root):
            if entry.getPath().getName().startswith("cut-"):
                fs.delete(entry.getPath(), True)

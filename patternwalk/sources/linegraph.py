"""The ``t / v / e`` line format of graph collections as a Spark data source, and other files.

A ``t # id`` line starts a graph, ``v id label`` is a vertex, ``e a b label`` an edge.
``format("linegraph")`` reads local or mounted files, one partition a file; :func:`read_lines`
reads any store Spark reads, one file a row.
"""

from __future__ import annotations

import glob
import os
import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage

from patternwalk.model import GraphDB, simplify

SCHEMA = "kind string, gid long, a long, b long, label string"


def parse_lines(lines: Iterator[str]) -> Iterator[tuple]:
    gid = None
    for line in lines:
        part = line.split()
        if not part or part[0] not in ("t", "v", "e"):
            continue
        if part[0] == "t":
            if part[-1].lstrip("-").isdigit() and int(part[-1]) >= 0:
                gid = int(part[-1])
        elif part[0] == "v":
            yield "v", gid, int(part[1]), None, " ".join(part[2:])
        else:
            yield "e", gid, int(part[1]), int(part[2]), " ".join(part[3:])


class LineGraphSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "linegraph"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema):
        return LineGraphReader(self.options["path"])

    def writer(self, schema, overwrite):
        return LineGraphWriter(self.options["path"])


class LineGraphReader(DataSourceReader):
    def __init__(self, path: str) -> None:
        self.path = path

    def partitions(self):
        found = sorted(glob.glob(os.path.join(self.path, "*"))) if os.path.isdir(self.path) else sorted(glob.glob(self.path))
        return [InputPartition(f) for f in found if not os.path.basename(f).startswith(("_", "."))]

    def read(self, partition):
        with open(partition.value) as lines:
            yield from parse_lines(lines)


class LineGraphWriter(DataSourceWriter):
    """Rows come sorted by graph within a partition; each task writes one file."""

    def __init__(self, path: str) -> None:
        self.path = path

    def write(self, rows):
        os.makedirs(self.path, exist_ok=True)
        name = os.path.join(self.path, f"part-{uuid.uuid4().hex}.lg")
        gid, n = None, 0
        with open(name + ".tmp", "w") as out:
            for r in rows:
                if r.gid != gid:
                    gid = r.gid
                    out.write(f"t # {gid}\n")
                out.write(f"v {r.a} {r.label}\n" if r.kind == "v" else f"e {r.a} {r.b} {r.label}\n")
                n += 1
        os.replace(name + ".tmp", name)
        return WriterCommitMessage()


def register(spark: SparkSession) -> None:
    spark.dataSource.register(LineGraphSource)


def rows_of(db: GraphDB) -> DataFrame:
    """A database as the format's rows, each graph together: vertices first."""
    v = db.vertices.select(F.lit("v").alias("kind"), "gid", F.col("vid").alias("a"), F.lit(None).cast("long").alias("b"), F.col("vlabel").alias("label"))
    e = db.edges.select(F.lit("e").alias("kind"), "gid", F.col("src").alias("a"), F.col("dst").alias("b"), F.col("elabel").alias("label"))
    return v.unionByName(e).repartition("gid").sortWithinPartitions("gid", F.desc("kind"), "a", "b")


def write(db: GraphDB, path: str) -> None:
    register(db.spark)
    rows_of(db).write.format("linegraph").mode("append").save(path)


def database(rows: DataFrame) -> GraphDB:
    v = rows.where("kind = 'v'").select("gid", F.col("a").alias("vid"), F.col("label").alias("vlabel"))
    e = rows.where("kind = 'e'").select("gid", F.col("a").alias("src"), F.col("b").alias("dst"), F.col("label").alias("elabel"))
    return GraphDB(v, simplify(e))


def read(spark: SparkSession, path: str) -> GraphDB:
    register(spark)
    return database(spark.read.format("linegraph").load(path))


def read_lines(spark: SparkSession, path: str) -> GraphDB:
    """The same from any store: whole files as rows, parsed in workers."""
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for text in frame["value"]:
                yield pd.DataFrame(list(parse_lines(iter(text.split("\n")))), columns=["kind", "gid", "a", "b", "label"], dtype=object)

    return database(spark.read.text(path, wholetext=True).mapInPandas(run, SCHEMA))


def read_edges(spark: SparkSession, path: str, fmt: str = "json") -> GraphDB:
    """Edge lists in JSON or CSV: ``gid, src, dst, elabel, src_label, dst_label``."""
    schema = "gid long, src long, dst long, elabel string, src_label string, dst_label string"
    rows = spark.read.schema(schema).csv(path, header=True) if fmt == "csv" else spark.read.schema(schema).json(path)
    v = rows.select("gid", F.col("src").alias("vid"), F.col("src_label").alias("vlabel")).unionByName(rows.select("gid", F.col("dst").alias("vid"), F.col("dst_label").alias("vlabel")))
    return GraphDB(v.groupBy("gid", "vid").agg(F.min("vlabel").alias("vlabel")), simplify(rows.select("gid", "src", "dst", "elabel")))


def save_packed(packed: DataFrame, path: str, buckets: int | None = None) -> None:
    """Packed graphs as Parquet; as a table bucketed by ``gid`` when ``buckets`` is given, so that walks join without an exchange."""
    if buckets:
        packed.write.bucketBy(buckets, "gid").sortBy("gid").mode("overwrite").saveAsTable(path)
    else:
        packed.write.mode("overwrite").parquet(path)


def write_dot(queue: DataFrame, path: str) -> None:
    """The patterns of a queue as one line of dot text each."""
    from patternwalk.functions.sql import _dot

    queue.select(_dot("code").alias("value")).write.mode("overwrite").text(path)


def write_by_size(patterns: DataFrame, path: str) -> None:
    """Patterns or samples as Parquet, a folder for each size ``p``."""
    patterns.write.partitionBy("p").mode("overwrite").parquet(path)

"""A plain-text graph format as a Spark data source: `t`, `v id label`, `e src dst label` records.

spark.dataSource.register(GraphText); spark.read.format("graphtext").load(path) gives kind, src,
dst, label; vertices have src = id and no dst. Each file is one partition. Writing makes one file
for each partition; a task writes under a name of its own, and only committed files are listed.
"""

from __future__ import annotations

import glob
import os
import uuid
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage

from ..model import PropertyGraph


@dataclass
class _File(InputPartition):
    path: str


@dataclass
class _Done(WriterCommitMessage):
    path: str


class GraphText(DataSource):
    @classmethod
    def name(cls) -> str:
        return "graphtext"

    def schema(self) -> str:
        return "kind string, src bigint, dst bigint, label string"

    def reader(self, schema):
        return _Reader(self.options["path"])

    def writer(self, schema, overwrite):
        return _Writer(self.options["path"], overwrite)


class _Reader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path.removeprefix("file://")

    def partitions(self):
        files = [self.path] if os.path.isfile(self.path) else sorted(glob.glob(f"{self.path}/*.graph"))
        return [_File(f) for f in files]

    def read(self, partition):
        with open(partition.path, encoding="utf-8") as lines:
            for line in lines:
                f = line.rstrip("\n").split(" ", 3)
                if f[0] == "v" and len(f) >= 2:
                    yield "v", int(f[1]), None, f[2] if len(f) > 2 and f[2] != "-" else None
                elif f[0] == "e" and len(f) >= 3:
                    yield "e", int(f[1]), int(f[2]), f[3] if len(f) > 3 and f[3] != "-" else None
                elif f[0] not in ("", "#", "t"):
                    raise ValueError(f"not a graph record: {line[:80]!r}")


class _Writer(DataSourceWriter):
    def __init__(self, path: str, overwrite: bool):
        self.path, self.overwrite = path.removeprefix("file://"), overwrite

    def write(self, rows):
        os.makedirs(self.path, exist_ok=True)
        name = f"{self.path}/part-{uuid.uuid4().hex}.tmp"
        with open(name, "w", encoding="utf-8") as out:
            for r in rows:
                label = "-" if r.label is None else r.label
                out.write(f"v {r.src} {label}\n" if r.kind == "v" else f"e {r.src} {r.dst} {label}\n")
        return _Done(name)

    def commit(self, messages):
        if self.overwrite:
            for f in glob.glob(f"{self.path}/*.graph"):
                os.remove(f)
        for m in messages:
            if m is not None:
                os.replace(m.path, m.path.removesuffix(".tmp") + ".graph")

    def abort(self, messages):
        for m in messages:
            if m is not None and os.path.exists(m.path):
                os.remove(m.path)


def read_graph(spark: SparkSession, path: str, directed: bool = False) -> PropertyGraph:
    spark.dataSource.register(GraphText)
    rows = spark.read.format("graphtext").load(path)
    edges = rows.where("kind = 'e'").select("src", "dst", F.col("label").alias("elabel"))
    if not directed:
        edges = edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "elabel"))
    return PropertyGraph(rows.where("kind = 'v'").select(F.col("src").alias("id"), "label"), edges.distinct(), directed)


def write_graph(g: PropertyGraph, path: str) -> None:
    """Undirected graphs keep one record for both arcs."""
    g.vertices.sparkSession.dataSource.register(GraphText)
    edges = g.edges if g.directed else g.edges.where("src <= dst")
    rows = g.vertices.select(F.lit("v").alias("kind"), F.col("id").alias("src"), F.lit(None).cast("long").alias("dst"), "label").unionByName(edges.select(F.lit("e").alias("kind"), "src", "dst", F.col("elabel").alias("label")))
    rows.write.format("graphtext").mode("append").save(path)


def read_edges(spark: SparkSession, path: str, fmt: str = "csv", **options) -> DataFrame:
    """src, dst, elabel from csv, json, orc or parquet, with a fixed schema."""
    reader = spark.read.options(**options)
    return (reader if fmt in ("parquet", "orc") else reader.schema("src bigint, dst bigint, elabel string")).format(fmt).load(path).select("src", "dst", "elabel")

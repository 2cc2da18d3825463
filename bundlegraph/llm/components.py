"""Connected components of an edge table, by alternating star contraction on the executors."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop_path, nullable, scratch_path


def connected(edges: DataFrame) -> DataFrame:
    """edges: a, b (long). Returns node, comp: the smallest node that is reachable.

    Each pass hangs the larger neighbours of a node, then the smaller ones, on its smallest
    neighbour; the number of passes is logarithmic in the length of chains. Every pass is
    written to the shared folder, so a lost executor costs one pass. Loops and nulls are ignored.
    """
    spark = edges.sparkSession

    def keep(df: DataFrame) -> tuple[DataFrame, str]:
        path = scratch_path(spark, "cc")
        df.write.parquet(path)
        return spark.read.schema(nullable(df.schema)).parquet(path), path

    # a > b everywhere below
    pairs = edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    cur, path = keep(pairs)
    mark = None
    while True:
        # large star: each neighbour above a node goes to the node's smallest neighbour
        both = cur.unionByName(cur.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("u"), F.least("a", "m").alias("m"))
        large = both.join(low, F.col("a") == F.col("u")).where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        # small star: each neighbour below a node, and the node, go to the smallest of them
        low = large.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("u"), "m")
        small = large.join(low, F.col("a") == F.col("u"))
        small = small.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(low.select(F.col("u").alias("a"), F.col("m").alias("b"))).where("a <> b").distinct()
        new, new_path = keep(small)
        seen = new.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        drop_path(spark, path)
        cur, path = new, new_path
        if tuple(seen) == mark:
            break
        mark = tuple(seen)
    roots = cur.select(F.col("b").alias("a"), "b").distinct()
    return cur.unionByName(roots).select(F.col("a").alias("node"), F.col("b").alias("comp"))

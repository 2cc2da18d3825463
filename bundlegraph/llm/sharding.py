"""Sharding: contiguous shards of near equal bytes, from prefix sums of per-partition totals.

Rows are range-partitioned by doc_id and each partition keeps its own running counts. The
partitions' totals give global prefix sums, and a row goes to the shard that holds the middle
of its bytes, so a shard differs from an equal share by less than its two boundary rows.
Equal texts get no special place: a group of copies may be cut by a boundary, which keeps
shards equal when one group holds a third of all rows.

Nulls: a null text has no bytes and counts as its 16 bytes of overhead; a null doc_id sorts
first. Repeated doc_ids are ordered by size and checksum. An empty table gives no rows. Of a text only
its length and checksum are kept, so very long ones cost no memory. Other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import running_offsets, written


def slim(docs: DataFrame, overhead: int = 16) -> DataFrame:
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select("doc_id", (F.octet_length(text) + F.lit(overhead)).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"))


def byte_shards(docs: DataFrame, shards: int = 40, overhead: int = 16) -> DataFrame:
    """doc_id, size, text_crc32, shard, slot (place in the shard, from 0)."""
    order = [F.col("doc_id").asc_nulls_first(), F.col("size"), F.col("text_crc32")]
    # doc_id, size and checksum only: the texts never move. Stored once, so that the ranges of
    # the totals and of the rows are the same ones.
    ranged = written(slim(docs, overhead).repartitionByRange(*order).withColumn("part", F.spark_partition_id()), "shard-rows")
    in_part = Window.partitionBy("part").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    local = ranged.select("*", F.coalesce(F.sum("size").over(in_part), F.lit(0)).alias("b"), F.coalesce(F.count("*").over(in_part), F.lit(0)).alias("r"))
    totals = ranged.groupBy("part").agg(F.sum("size").alias("bytes"), F.count("*").alias("rows")).withColumn("all", F.lit(1))
    before = running_offsets(totals, ["all"], "part", ["bytes", "rows"])
    total = totals.agg(F.sum("bytes")).first()[0] or 1
    middle = (F.col("b") + F.col("bytes_before")).cast("decimal(38,0)") * 2 + F.col("size")
    placed = local.join(before, "part").select(
        "doc_id", "size", "text_crc32", (F.col("r") + F.col("rows_before")).alias("row"),
        F.least(F.lit(shards - 1), F.floor(middle * shards / F.lit(2 * total).cast("decimal(38,0)")).cast("int")).cast("int").alias("shard"),
    )
    placed = written(placed, "shard-placed")
    first = placed.groupBy("shard").agg(F.min("row").alias("first"))  # at most `shards` rows
    return placed.join(F.broadcast(first), "shard").select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("row") - F.col("first")).alias("slot"), F.lit(None).cast("int").alias("grown_shard"))

"""Mixing sources to target weights by systematic sampling, in DataFrame functions only.

Targets: sources in code point order (null last) weigh 3, 1, 2, repeating, and share a budget of
words; a target stops at `most` times its source's words and the excess is shared again by weight.
That ends at one water level, which windows over the source totals find directly.

Sampling: within a source each document expects target / size of source copies. Documents stand
in order of (size, doc_id); the expected copies are prefix-summed, one random offset is added for
each source, and a copy is emitted at each integer that a document's stretch crosses. Standing in
order of size makes the words taken as even as the copies. A hot source is cut into many ranges
by (source, size, doc_id), so no task holds a source.

Nulls: a null text has no words; a null source is a source of its own; a null doc_id sorts first.
Repeated rows count each. A source without words has target 0 and nothing is taken from it.
An empty table gives no rows. Of a text of any length only its number of words is moved until `mix`
joins the copies to the documents. Other columns pass through `mix` and are ignored by `allot`.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, running_offsets, trim, written

# fixed values: the weights that repeat over the sources in order
WEIGHTS = (3, 1, 2)


def words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def targets(totals: DataFrame, share: float, most: float, weights: tuple[int, ...] = WEIGHTS) -> DataFrame:
    """totals: src, no_src, source_size, one row a source. Adds target."""
    in_order = Window.partitionBy().orderBy("no_src", "src")
    weigh = F.element_at(F.array(*[F.lit(w) for w in weights]), (F.pmod(F.row_number().over(in_order) - 1, F.lit(len(weights))) + 1).cast("int"))
    s = totals.withColumn("w", weigh).withColumn("cap", F.col("source_size") * F.lit(float(most)))
    full = Window.partitionBy().orderBy(F.col("cap") / F.col("w"), "no_src", "src")
    s = s.withColumn("all_words", F.sum("source_size").over(Window.partitionBy()) * F.lit(float(share)))
    level = (F.col("all_words") - F.coalesce(F.sum("cap").over(full.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))) / F.sum("w").over(full.rowsBetween(0, Window.unboundedFollowing))
    s = s.withColumn("level", level).withColumn("n", F.row_number().over(full))
    found = F.min(F.when(F.col("level") <= F.col("cap") / F.col("w"), F.struct("n", "level"))).over(Window.partitionBy())
    return s.select("src", "no_src", "source_size", F.coalesce(F.least(F.col("cap"), F.col("w") * found["level"]), F.col("cap")).alias("target"))


def allot(rows: DataFrame, keep: list[str], share: float = 1.5, most: float = 2.0, seed: str = "mix") -> DataFrame:
    """rows: doc_id, source, size and the columns of `keep`. Adds source_size, target, copies."""
    src = [F.coalesce(F.col("source"), F.lit("")).alias("src"), F.col("source").isNull().alias("no_src")]
    order = ["no_src", "src", "size", F.col("doc_id").asc_nulls_first(), *keep]
    # stored once: the ranges of the counts and of the rows must be the same ones
    ranged = written(rows.select("doc_id", "size", *keep, *src).repartitionByRange(*order).withColumn("part", F.spark_partition_id()), "mix-rows")
    by_part = ranged.groupBy("no_src", "src", "part").agg(F.count("*").alias("n"), F.sum("size").alias("source_size"))
    before = running_offsets(by_part, ["no_src", "src"], "part", ["n"])
    aims = targets(by_part.groupBy("no_src", "src").agg(F.sum("source_size").alias("source_size")), share, most)
    nth = F.row_number().over(Window.partitionBy("no_src", "src", "part").orderBy("size", F.col("doc_id").asc_nulls_first(), *keep)) + F.col("n_before")
    offset = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.col("src"), F.when(F.col("no_src"), ":null").otherwise(""))), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)
    per = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    return (
        ranged.join(before, ["no_src", "src", "part"]).join(aims, ["no_src", "src"])
        .withColumn("nth", nth).withColumn("per", per).withColumn("u", offset)
        .select("doc_id", F.when(~F.col("no_src"), F.col("src")).alias("source"), "size", *keep, "source_size", "target", (F.floor(F.col("per") * F.col("nth") + F.col("u")) - F.floor(F.col("per") * (F.col("nth") - 1) + F.col("u"))).alias("copies"))
    )


def mix_report(docs: DataFrame, share: float = 1.5, most: float = 2.0) -> DataFrame:
    """What the mix takes from each document, without moving a text."""
    sized = docs.select("doc_id", "source", words(F.col("text")).alias("size"))
    return allot(sized, [], share, most).select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).alias("taken"))


def mix(docs: DataFrame, share: float = 1.5, most: float = 2.0) -> DataFrame:
    """The mixed documents themselves: each row as often as it is taken, columns as they came."""
    trim()
    held = written(docs.withColumn("__row", F.monotonically_increasing_id()), "mix-docs")
    sized = held.select("doc_id", "source", "__row", words(F.col("text")).alias("size"))
    times = allot(sized, ["__row"], share, most).where("copies > 0").select(F.col("__row").alias("__r"), "copies")
    joined = held.join(times, F.col("__row") == F.col("__r"))
    return joined.withColumn("__copy", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int")))).select(*docs.columns)


REPORT_SQL = r"""
WITH d AS (SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS i FROM d GROUP BY source),
w AS (SELECT *, [3, 1, 2][1 + i % 3] AS w, source_size * 2.0::DOUBLE AS cap, sum(source_size) OVER () * 1.5::DOUBLE AS total FROM s),
l AS (SELECT *, row_number() OVER (ORDER BY cap / w, source NULLS LAST) AS n,
  (total - coalesce(sum(cap) OVER (ORDER BY cap / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
  / sum(w) OVER (ORDER BY cap / w, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM w),
t AS (SELECT source, source_size, coalesce(least(cap, w * (SELECT min_by(level, n) FROM l WHERE level <= cap / w)), cap) AS target,
  CAST('0x' || substr(md5('mix:' || coalesce(source, '') || CASE WHEN source IS NULL THEN ':null' ELSE '' END), 1, 8) AS BIGINT) / 4294967296.0::DOUBLE AS u FROM l),
r AS (SELECT d.doc_id, d.size, t.source_size, t.target, t.u, CASE WHEN t.source_size > 0 THEN t.target / t.source_size ELSE 0 END AS per,
  row_number() OVER (PARTITION BY d.source ORDER BY d.size, d.doc_id NULLS FIRST) AS nth FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, source_size, target, CAST((floor(per * nth + u) - floor(per * (nth - 1) + u)) * size AS BIGINT) AS taken FROM r
"""

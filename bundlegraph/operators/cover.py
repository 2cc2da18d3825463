"""Undirected graphs made of sets whose members are all linked, without the pairs of large sets.

Large sets stay sets: vertices that lie in the same large sets are of one kind, and two kinds are
linked if they share a set, so what kinds say of all their members is one step. Only pairs of small
sets that no large set links are arcs. Numbers of arcs and of triangles are exact: those of large
sets come from blocks of kinds, those with one or two arcs from the kinds at the ends of the arcs,
those of three arcs from the matching engine. Kinds are collected on the driver; they grow with the
mixtures of large sets that occur, not with the sets' members.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.scratch import scratch_path
from ..model import PropertyGraph
from ..workload import shape

#: Sets of more members than this are large.
SMALL = 64
#: Kinds that a task takes against each other at once.
BLOCK = 512
_WHOLE = "decimal(38,0)"


@dataclass
class Cover:
    """members: id, sets (numbers of its large sets); arcs: src, dst of both directions."""

    members: DataFrame
    arcs: DataFrame
    path: str | None = None

    def store(self, keep: bool = False) -> "Cover":
        if self.path:
            return self
        spark = self.members.sparkSession
        path = scratch_path(spark, "cover", keep)
        out = []
        for name, df in (("members", self.members), ("arcs", self.arcs)):
            df.write.parquet(f"{path}/{name}")
            out.append(spark.read.schema(df.schema).parquet(f"{path}/{name}"))
        return Cover(*out, path)

    def kinds(self) -> tuple[DataFrame, list[np.ndarray], np.ndarray]:
        """(id, kind) of the members, and the sets and the size of each kind."""
        rows = self.members.groupBy("sets").agg(F.count("*").alias("n")).orderBy("sets").collect()  # a row a kind
        spark = self.members.sparkSession
        numbered = spark.createDataFrame([(k, r.sets) for k, r in enumerate(rows)], "kind int, sets array<int>")
        return self.members.join(F.broadcast(numbered), "sets").select("id", "kind"), [np.array(r.sets) for r in rows], np.array([r.n for r in rows], dtype=float)

    def summary(self, times: int, modulus: int) -> DataFrame:
        """n and mark: the number of arcs and the sum of (times * src + dst) mod `modulus` over them."""
        spark = self.members.sparkSession
        of, sets, sizes = self.kinds()
        mark = lambda a, b: F.pmod(a * times + b, F.lit(modulus))
        parts = [self.arcs.agg(F.count("*").cast(_WHOLE).alias("n"), F.sum(mark(F.col("src"), F.col("dst"))).cast(_WHOLE).alias("mark"))]
        parts.append(self.members.agg((-F.count("*")).cast(_WHOLE).alias("n"), (-F.sum(mark(F.col("id"), F.col("id")))).cast(_WHOLE).alias("mark")))
        if sets:
            shared, last = spark.sparkContext.broadcast(sets), (len(sets) - 1) // BLOCK
            # how often a kind has a remainder; each block of kinds meets each block
            often = of.groupBy("kind", F.pmod("id", F.lit(modulus)).alias("r")).agg(F.count("*").alias("n"))
            mine, every = F.floor(F.col("kind") / BLOCK), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(last).cast("long")))
            left = often.select(mine.alias("i"), every.alias("j"), F.lit(0).alias("side"), "kind", "r", "n")
            right = often.select(every.alias("i"), mine.alias("j"), F.lit(1).alias("side"), "kind", "r", "n")

            def meet(df: pd.DataFrame) -> pd.DataFrame:
                ends = []
                for side in (0, 1):
                    d = df[df["side"] == side]
                    kinds, at = np.unique(d["kind"].to_numpy(), return_inverse=True)
                    table = np.zeros((len(kinds), modulus))
                    table[at, d["r"].to_numpy()] = d["n"].to_numpy()
                    ends.append((kinds, table))
                (a, x), (b, y) = ends
                pairs = x.T @ (linked(shared.value, a, b) @ y)  # by both remainders
                r = np.arange(modulus)
                worth = (times * r[:, None] + r[None, :]) % modulus
                return pd.DataFrame({"n": [str(sum(map(int, pairs.sum(1))))], "mark": [str(sum(map(int, (pairs * worth).sum(1))))]})

            parts.append(left.unionByName(right).groupBy("i", "j").applyInPandas(meet, "n string, mark string").select(F.col("n").cast(_WHOLE).alias("n"), F.col("mark").cast(_WHOLE).alias("mark")))
        out = reduce(DataFrame.unionByName, parts).agg(F.sum("n").cast("long").alias("n"), F.sum("mark").cast("long").alias("mark"))
        return out.where("n > 0")

    def triangles(self) -> DataFrame:
        """n: three different vertices, in order, each two of them linked."""
        from .match import match

        spark = self.members.sparkSession
        of, sets, sizes = self.kinds()
        ids = self.arcs.select(F.col("src").alias("id")).distinct().withColumn("label", F.lit(None).cast("string"))
        loose = match(PropertyGraph(ids, self.arcs.withColumn("elabel", F.lit("LOOSE"))), shape("triangle")).count()
        parts = [loose.select(F.col("n").cast(_WHOLE).alias("n"))]
        if sets:
            shared = spark.sparkContext.broadcast((sets, sizes))
            far = of.select(F.col("id").alias("dst"), F.col("kind").alias("b"))
            near = self.arcs.join(far, "dst").select("src", "b")
            # pairs of kinds that arcs lead between, and one row for each block of kinds without any
            between = near.join(of.select(F.col("id").alias("src"), F.col("kind").alias("a")), "src").groupBy("a", "b").agg(F.count("*").alias("arcs"))
            blocks = spark.range((len(sets) - 1) // BLOCK + 1).select(F.col("id").alias("i"), F.lit(-1).alias("a"), F.lit(-1).alias("b"), F.lit(0).cast("long").alias("arcs"))
            rows = between.select(F.floor(F.col("a") / BLOCK).alias("i"), "a", "b", "arcs").unionByName(blocks)

            def block(df: pd.DataFrame) -> pd.DataFrame:
                (sets, sizes), lo = shared.value, int(df["i"].iloc[0]) * BLOCK
                every = np.arange(len(sets))
                mine = every[lo : lo + BLOCK]
                to = linked(sets, mine, every)
                a, b, arcs = (df[df["a"] >= 0][c].to_numpy() for c in ("a", "b", "arcs"))
                closed, one = np.zeros(len(mine)), 0
                for start in range(0, len(sets), BLOCK):
                    theirs = every[start : start + BLOCK]
                    common = (to * sizes) @ linked(sets, theirs, every).T  # vertices linked with both kinds
                    closed += (to[:, theirs] * sizes[theirs] * common).sum(1)
                    here = (b >= start) & (b < start + BLOCK)
                    one += sum(int(n) * int(c) for n, c in zip(arcs[here], common[a[here] - lo, b[here] - start]))
                # a kind is linked with itself: choices that take one vertex twice go
                found = sum(int(n) * (int(c) - 3 * int(p) + 2) for n, c, p in zip(sizes[mine], closed, to @ sizes))
                return pd.DataFrame({"n": [str(found + 3 * one)]})

            parts.append(rows.groupBy("i").applyInPandas(block, "n string").select(F.col("n").cast(_WHOLE).alias("n")))
            around = near.groupBy("src", "b").agg(F.count("*").alias("k")).groupBy("src").agg(F.collect_list("b").alias("b"), F.collect_list("k").alias("k"))

            def two(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                sets, total = shared.value[0], 0
                for batch in batches:
                    for b, k in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                        n = np.array(k, dtype=float)
                        total += int(n @ linked(sets, b, b) @ n) - sum(k)
                yield pa.RecordBatch.from_pydict({"n": pa.array([str(3 * total)])})

            parts.append(around.select("b", "k").mapInArrow(two, "n string").select(F.col("n").cast(_WHOLE).alias("n")))
        return reduce(DataFrame.unionByName, parts).agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))


def linked(sets: list[np.ndarray], a: Iterable[int], b: Iterable[int]) -> np.ndarray:
    """1.0 where a kind of a and a kind of b share a set."""
    used, at = np.unique(np.concatenate([sets[k] for k in [*a, *b]] or [np.zeros(0, int)]), return_inverse=True)
    ends, start = [], 0
    for kinds in (a, b):
        rows = np.zeros((len(kinds), len(used)), dtype=np.float32)
        for k, kind in enumerate(kinds):
            stop = start + len(sets[kind])
            rows[k, at[start:stop]] = 1
            start = stop
        ends.append(rows)
    return (ends[0] @ ends[1].T > 0).astype(float)


def cover(sets: DataFrame, small: int = SMALL) -> Cover:
    """sets: id, key, each pair once; members of one key are all linked."""
    counts = sets.groupBy("key").agg(F.count("*").alias("c")).where("c > 1")
    large = counts.where(F.col("c") > small).select("key", (F.row_number().over(Window.orderBy("key")) - 1).alias("k"))
    members = sets.join(F.broadcast(large), "key").groupBy("id").agg(F.array_sort(F.collect_list("k")).alias("sets"))
    rest = sets.join(F.broadcast(large.select("key")), "key", "left_anti")  # before they are dealt by key
    rest = rest.join(counts.where(F.col("c") <= small).select("key"), "key").join(members, "id", "left")
    groups = rest.groupBy("key").agg(F.collect_list(F.struct("id", F.coalesce("sets", F.array().cast("array<int>")).alias("sets"))).alias("g"))
    pairs = groups.select("g", F.explode("g").alias("x")).select("x", F.explode("g").alias("y")).where("x.id <> y.id AND NOT arrays_overlap(x.sets, y.sets)")
    return Cover(members, pairs.select(F.col("x.id").alias("src"), F.col("y.id").alias("dst")).distinct())

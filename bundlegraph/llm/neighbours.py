"""Approximate nearest neighbours by inner product: multiprobe p-stable hashing.

Vectors are lifted to one length (one more component), which turns the largest inner product
into the smallest distance. Each of `tables` tables hashes a vector by `hashes` Gaussian
projections, offset and cut into slots of width w. For a query the chance of every nearby bucket
to hold a neighbour of the expected closeness is the product of its slots' chances; buckets are
visited in falling order until their chances add up to the table's share of `recall`. What the
tables find is merged and ranked by exact inner products. A query that finds fewer than k is
searched again over all buckets, so none comes back short.

Equal vectors are one entry with its k + 1 smallest ids (no more can be among k nearest). Work is
dealt by cells (the first two slots of a bucket); a cell with many vectors or many queries is
cut into blocks, so a task's matrices are bounded. Slot width and closeness come from a sample of
at most `sample` vectors; every vector is indexed.

Nulls: null, zero and non-finite vectors take no part, nor do those of another length than the
commonest one (the larger at a tie), nor null ids. A repeated id counts once for each vector that
it has. Fewer candidates than k: all of them. Empty tables give no rows. Ties go to the smaller id.
Vectors of any length are read whole; a block holds ROWS of them. Other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import written

ROWS, QUERIES = 4096, 1024  # vectors and queries of a block
MOST_CELLS = 200_000  # a broadcast table of cells has no more rows
ASKS = 64  # queries of a task that makes probes, until there are MOST_TASKS
MOST_TASKS = 20_000


def _phi(x: np.ndarray) -> np.ndarray:
    """Normal distribution function (Abramowitz and Stegun 7.1.26, error below 1e-6)."""
    z = np.abs(x) / math.sqrt(2)
    t = 1 / (1 + 0.3275911 * z)
    erf = 1 - t * (0.254829592 + t * (-0.284496736 + t * (1.421413741 + t * (-1.453152027 + t * 1.061405429)))) * np.exp(-z * z)
    return np.where(x < 0, 1 - erf, 1 + erf) / 2


class Hashing:
    """The tables' projections, and what the sample says about widths and neighbours."""

    def __init__(self, sample: np.ndarray, n: int, top: float, k: int, tables: int, hashes: int, recall: float, seed: int = 3):
        rng = np.random.default_rng(seed)
        self.tables, self.hashes, self.top = tables, hashes, top
        self.a = rng.normal(size=(tables, hashes, sample.shape[1] + 1))
        lifted = self.lift(sample)
        self.w = 2.0 * (lifted @ self.a.reshape(tables * hashes, -1).T).std(axis=0).reshape(tables, hashes) + 1e-12
        self.b = rng.uniform(size=(tables, hashes)) * self.w
        # slots beyond nearly all of the sample are one open slot on each side, so axes stay short
        self.lo, self.hi = np.full((tables, hashes), -(1 << 40)), np.full((tables, hashes), 1 << 40)
        seen = np.stack([self.slots(sample, t) for t in range(tables)])
        self.lo, self.hi = np.quantile(seen, 0.005, axis=1).astype(np.int64) - 1, np.quantile(seen, 0.995, axis=1).astype(np.int64) + 1
        ask = sample[:400]
        cos = (ask / np.linalg.norm(ask, axis=1, keepdims=True)) @ sample.T / top
        cos[np.arange(len(ask)), np.arange(len(ask))] = -2
        kth = np.quantile(cos[cos > -2], max(0.0, 1 - 1.5 * k / max(n, 1.5 * k))) if cos.size > len(ask) else 0.0
        self.rho = float(np.clip(kth, 0.0, 0.999))
        self.share = 1 - (1 - recall) ** (1 / tables)

    def cells(self) -> int:
        """How many cells there can be: the first two axes end in open slots."""
        return int(sum(np.prod((self.hi - self.lo + 1)[t, : min(2, self.hashes)]) for t in range(self.tables)))

    def lift(self, x: np.ndarray) -> np.ndarray:
        rest = np.sqrt(np.maximum(self.top**2 - (x * x).sum(axis=1), 0.0))
        return np.concatenate([x, rest[:, None]], axis=1)

    def slots(self, x: np.ndarray, table: int) -> np.ndarray:
        return np.clip(np.floor((self.lift(x) @ self.a[table].T + self.b[table]) / self.w[table]).astype(np.int64), self.lo[table], self.hi[table])

    @staticmethod
    def names(slots: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Cell (first two slots) and bucket within it, one number each; slots lie within +-500."""
        s = np.clip(slots, -500, 499) + 500
        cell, bucket = s[:, 0], np.zeros(len(s), dtype=np.int64)
        for i in range(1, s.shape[1]):
            if i == 1:
                cell = cell * 1000 + s[:, 1]
            else:
                bucket = bucket * 1000 + s[:, i]
        return cell, bucket

    def probes(self, q: np.ndarray, table: int) -> tuple[np.ndarray, np.ndarray]:
        """Slots of the buckets to visit for one query, likeliest first, and their chances."""
        a, w, b = self.a[table], self.w[table], self.b[table]
        qs = np.append(q * (self.top / np.linalg.norm(q)), 0.0)
        dot, d = a @ qs, a.shape[1]
        mean = self.rho * dot + b
        var = ((a * a).sum(axis=1) * self.top**2 - dot * dot).clip(1e-12) / (d - 1) * (1 - self.rho**2)
        sd = np.sqrt(var)
        axes, chances = [], []
        for i in range(self.hashes):
            at = np.arange(self.lo[table, i], self.hi[table, i] + 1)
            edge = _phi((np.arange(at[0], at[-1] + 2) * w[i] - mean[i]) / sd[i])
            edge[0], edge[-1] = 0.0, 1.0
            axes.append(at)
            chances.append(np.diff(edge))
        p = chances[0]
        for c in chances[1:]:
            p = np.multiply.outer(p, c)
        flat = p.ravel()
        order = np.argsort(-flat, kind="stable")
        reach = np.cumsum(flat[order])
        order = order[: int(np.searchsorted(reach, self.share * min(1.0, reach[-1]))) + 1]
        at = np.unravel_index(order, p.shape)
        return np.stack([axes[i][at[i]] for i in range(self.hashes)], axis=1), flat[order]


def usable(df: DataFrame, key: str, vector: str) -> DataFrame:
    """id, v (array of double): the vectors that take part."""
    v = F.transform(F.col(vector), lambda x: x.cast("double"))
    rows = df.select(F.col(key).cast("long").alias("id"), v.alias("v")).where("id IS NOT NULL AND v IS NOT NULL")
    rows = rows.where(F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("v", lambda x: x != 0.0))
    lengths = rows.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), F.desc("d")).first()
    return rows.where(F.size("v") == (lengths.d if lengths else -1))


def _search(index: DataFrame, queries: DataFrame, k: int, cells: int) -> DataFrame:
    """index: t, cell, bucket, id, ids, v. queries: t, cell, buckets (null: all), q, qv. Best k + 1 of each block."""
    rows = index.groupBy("t", "cell").agg(F.count("*").alias("n"))
    asks = queries.groupBy("t", "cell").agg(F.count("*").alias("m"))
    # one row a cell, of which the hashing has `cells` at most: small enough to be broadcast, so a hot
    # cell's rows are dealt into blocks where they are and first move as bounded blocks
    sized = rows.join(asks, ["t", "cell"]).select("t", "cell", F.ceil(F.col("n") / ROWS).cast("int").alias("parts"), F.ceil(F.col("m") / QUERIES).cast("int").alias("asks"))
    small = (lambda df: F.broadcast(df)) if cells <= MOST_CELLS else (lambda df: df)
    left = index.join(small(sized), ["t", "cell"]).withColumn("part", F.pmod(F.xxhash64("id", F.lit("r")), F.col("parts")).cast("int"))
    left = left.withColumn("ask", F.explode(F.sequence(F.lit(0), F.col("asks") - 1))).drop("parts", "asks")
    right = queries.join(small(sized), ["t", "cell"]).withColumn("ask", F.pmod(F.xxhash64("q", F.lit("q")), F.col("asks")).cast("int"))
    right = right.withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).drop("parts", "asks")

    def block(x: pd.DataFrame, y: pd.DataFrame) -> pd.DataFrame:
        if not len(x) or not len(y):
            return pd.DataFrame({"q": [], "id": [], "score": []}).astype({"q": "int64", "id": "int64", "score": "float64"})
        vec, ask = np.stack(x["v"].to_numpy()), np.stack(y["qv"].to_numpy())
        ids, bucket = x["id"].to_numpy(), x["bucket"].to_numpy()
        names, where = np.unique(bucket, return_inverse=True)
        seen = np.zeros((len(y), len(names)), dtype=bool)
        for i, b in enumerate(y["buckets"]):
            if b is None:
                seen[i] = True
            else:
                at = np.searchsorted(names, b)
                at[at == len(names)] = 0
                seen[i, at[names[at] == b]] = True
        score = np.full((len(y), len(x)), -np.inf)
        for j in range(len(names)):
            cols, who = np.flatnonzero(where == j), np.flatnonzero(seen[:, j])
            if who.size:
                score[np.ix_(who, cols)] = ask[who] @ vec[cols].T
        most = min(k + 1, len(x))
        floor = np.partition(score, len(x) - most, axis=1)[:, len(x) - most]
        with np.errstate(invalid="ignore"):
            slack = 1e-9 * np.maximum(1.0, np.abs(floor))
            qi, xi = np.nonzero((score >= (floor - np.where(np.isfinite(floor), slack, 0.0))[:, None]) & np.isfinite(score))
        exact = np.zeros(len(qi))
        for j in range(vec.shape[1]):  # one order of adding for every pair, so equal vectors score alike
            exact += ask[qi, j] * vec[xi, j]
        out = pd.DataFrame({"q": y["q"].to_numpy()[qi], "id": ids[xi], "score": exact}).sort_values(["q", "score", "id"], ascending=[True, False, True], kind="stable")
        return out.groupby("q", sort=False).head(k + 1)

    keys = ["t", "cell", "part", "ask"]
    left = left.select(*keys, "bucket", "id", "v")
    return left.groupBy(*keys).cogroup(right.select(*keys, "buckets", "q", "qv").groupBy(*keys)).applyInPandas(block, "q long, id long, score double")


def nearest(df: DataFrame, key: str, vector: str, is_query, k: int = 20, tables: int = 2, hashes: int = 6, recall: float = 0.98, sample: int = 2000) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest found of each row for which is_query holds."""
    spark = df.sparkSession
    rows = written(usable(df, key, vector), "vectors")
    first = Window.partitionBy("v").orderBy("id")
    # the window's limit is applied on both sides of its shuffle, so a hot vector moves k + 1 rows a task
    few = rows.select("id", "v").distinct().withColumn("nth", F.row_number().over(first)).where(F.col("nth") <= k + 1)
    entries = written(few.groupBy("v").agg(F.min("id").alias("id"), F.array_sort(F.collect_list("id")).alias("ids")), "entries")
    facts = entries.agg(F.count("*").alias("n"), F.max(F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x)).alias("top")).first()
    schema = "query_id long, rank int, vec_id long, score double"
    if not facts.n:
        return spark.createDataFrame([], schema)
    keep = min(1.0, sample / facts.n)
    some = entries.where(F.pmod(F.xxhash64("id", F.lit("s")), F.lit(1 << 30)) <= int(keep * (1 << 30))).select("id", "v").orderBy(F.xxhash64("id")).limit(sample).collect()
    hashing = Hashing(np.array([r.v for r in some]), facts.n, math.sqrt(facts.top), k, tables, hashes, recall)
    shared = spark.sparkContext.broadcast(hashing)  # a few hundred projections

    def index(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            if len(part):
                x = np.stack(part["v"].to_numpy())
                for t in range(shared.value.tables):
                    cell, bucket = shared.value.names(shared.value.slots(x, t))
                    yield pd.DataFrame({"t": np.int32(t), "cell": cell, "bucket": bucket, "id": part["id"], "v": part["v"]})

    def probe(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            out = []
            for q, v in zip(part["id"], part["v"]):
                for t in range(shared.value.tables):
                    cell, bucket = shared.value.names(shared.value.probes(np.asarray(v), t)[0])
                    order = np.argsort(cell, kind="stable")
                    for at in np.split(order, np.flatnonzero(np.diff(cell[order])) + 1):
                        out.append((np.int32(t), cell[at[0]], bucket[at], q, v))
            if out:
                yield pd.DataFrame(out, columns=["t", "cell", "buckets", "q", "qv"])

    asked = written(rows.where(is_query(F.col("id"))).select("id", "v").distinct(), "ann-asked")
    tasks = max(1, min(MOST_TASKS, -(-asked.count() // ASKS)))
    table = written(entries.select("id", "v").mapInPandas(index, "t int, cell long, bucket long, id long, v array<double>"), "ann-index")
    probes = written(asked.repartition(tasks, "id").mapInPandas(probe, "t int, cell long, buckets array<long>, q long, qv array<double>"), "ann-probes")
    ids = entries.select("id", "ids")

    def ranked(found: DataFrame) -> DataFrame:
        best = Window.partitionBy("q").orderBy(F.desc("score"), "id")
        found = found.distinct().withColumn("nth", F.row_number().over(best)).where(F.col("nth") <= k + 1)
        each = found.join(ids, "id").select("q", "score", F.explode("ids").alias("vec_id")).where("vec_id <> q").groupBy("q", "vec_id").agg(F.max("score").alias("score"))
        order = Window.partitionBy("q").orderBy(F.desc("score"), "vec_id")
        return each.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select(F.col("q").alias("query_id"), "rank", "vec_id", "score")

    got = written(ranked(_search(table, probes, k, hashing.cells())), "ann-found")
    others = rows.select("id").distinct().count() - 1
    full = got.groupBy("query_id").count().where(F.col("count") >= min(k, others)).select(F.col("query_id").alias("id"))
    short = written(asked.join(full, "id", "left_anti"), "ann-short")
    if short.isEmpty():
        return got
    # the exact way for the rest: every bucket of one table
    cells = [r.cell for r in table.where("t = 0").select("cell").distinct().limit(MOST_CELLS + 1).collect()]
    if len(cells) > MOST_CELLS:
        raise ValueError("the hashing has too many cells; use wider slots")
    everywhere = short.select(F.lit(0).alias("t"), F.explode(F.lit(cells).cast("array<long>")).alias("cell"), F.lit(None).cast("array<long>").alias("buckets"), F.col("id").alias("q"), F.col("v").alias("qv"))
    everywhere = written(everywhere, "ann-everywhere")
    rest = ranked(_search(table.where("t = 0"), everywhere, k, len(cells)))
    return got.join(short.select(F.col("id").alias("query_id")), "query_id", "left_anti").select("query_id", "rank", "vec_id", "score").unionByName(rest)

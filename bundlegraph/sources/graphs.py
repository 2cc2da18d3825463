"""Graphs carried by relational, event, text, page and conversation tables.

Every builder returns a PropertyGraph with bigint ids. Ids of different tables are kept apart by
a tag: id = tag * TAG + key. Undirected graphs store both arcs; arcs are distinct.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.scratch import fingerprint, path_exists, written
from ..model import PropertyGraph
from ..operators.cover import Cover, cover
from ..operators.dense import BLOCK, triangles

TAG = 1_000_000_000_000
TAGS = {"region": 1, "nation": 2, "customer": 3, "supplier": 4, "part": 5, "orders": 6}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


_HELD: dict[tuple, tuple] = {}


def remembered(spark: SparkSession, sf_dir: str, name: str, tables: tuple[str, ...], build: Callable[[], PropertyGraph | Cover]) -> PropertyGraph | Cover:
    """A graph that is stored once for a session and built again when a table's files have changed or
    the stored arcs are gone."""
    files = tuple(fingerprint(spark, f"{sf_dir}/{t}.parquet") for t in tables)
    key = (spark.sparkContext.applicationId, name, sf_dir)
    held = _HELD.get(key)
    if held is None or held[0] != files or not path_exists(spark, held[1].path):
        _HELD[key] = held = (files, build().store(keep=True))
    return held[1]


def tagged(kind: str, key: str) -> Column:
    return F.col(key).cast("long") + F.lit(TAGS[kind] * TAG)


def undirected(vertices: DataFrame, pairs: DataFrame, elabel: str) -> PropertyGraph:
    """pairs: src, dst in one direction."""
    both = pairs.unionByName(pairs.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    return PropertyGraph(vertices, both.withColumn("elabel", F.lit(elabel)))


#: Kinds of arcs of the trade graph: table, its two keys and the labels at both ends.
TRADE_KINDS = {
    "IN_REGION": ("nation", "n_nationkey", "n_regionkey", ("nation", "region")),
    "LIVES_IN": ("customer", "c_custkey", "c_nationkey", ("customer", "nation")),
    "BASED_IN": ("supplier", "s_suppkey", "s_nationkey", ("supplier", "nation")),
    "PLACED": ("orders", "o_custkey", "o_orderkey", ("customer", "orders")),
    "CONTAINS": ("lineitem", "l_orderkey", "l_partkey", ("orders", "part")),
    "SHIPPED_BY": ("lineitem", "l_orderkey", "l_suppkey", ("orders", "supplier")),
    "SUPPLIES": ("lineitem", "l_suppkey", "l_partkey", ("supplier", "part")),
}
TRADE_TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem")


def trade(spark: SparkSession, sf_dir: str, with_lines: bool = False) -> PropertyGraph:
    """Directed, edge-labelled: regions, nations, customers, suppliers, parts, orders.

    with_lines: only orders and parts, whose arcs carry quantity and discount of their line.
    """
    t = lambda name: load(spark, sf_dir, name)
    keys = {"region": "r_regionkey", "nation": "n_nationkey", "customer": "c_custkey", "supplier": "s_suppkey", "part": "p_partkey", "orders": "o_orderkey"}
    sub = {"customer": "c_mktsegment", "part": "p_type", "orders": "o_orderstatus"}

    def side(k: str, c: str) -> DataFrame:
        return t(k).select(tagged(k, c).alias("id"), F.lit(k).alias("label"), F.col(c).cast("long").alias("key"), (F.col(sub[k]) if k in sub else F.lit(None).cast("string")).alias("sub"))

    vertices = reduce(DataFrame.unionByName, [side(k, c) for k, c in keys.items()])
    if with_lines:
        lines = t("lineitem").select(tagged("orders", "l_orderkey").alias("src"), tagged("part", "l_partkey").alias("dst"), F.lit("CONTAINS").alias("elabel"), F.col("l_quantity").alias("quantity"), F.col("l_discount").alias("discount"))
        return PropertyGraph(vertices.where("label IN ('orders', 'part')"), lines, directed=True)
    arcs = [t(table).select(tagged(ends[0], a).alias("src"), tagged(ends[1], b).alias("dst"), F.lit(e).alias("elabel")) for e, (table, a, b, ends) in TRADE_KINDS.items()]
    types = {e: ends for e, (_, _, _, ends) in TRADE_KINDS.items()}
    return PropertyGraph(vertices, reduce(DataFrame.unionByName, arcs), directed=True, types=types)


def copart(spark: SparkSession, sf_dir: str, min_shared: int = 1, label: str = "p_type") -> PropertyGraph:
    """Parts that share at least `min_shared` orders. An order's parts pair up with each other, so
    the work grows with the square of an order's length (bounded by the order, not by a hub)."""
    op = load(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("o"), F.col("l_partkey").cast("long").alias("p")).distinct()
    pairs = op.select("o", F.col("p").alias("src")).join(op.select("o", F.col("p").alias("dst")), "o").where("src < dst")
    pairs = pairs.groupBy("src", "dst").agg(F.count("*").alias("c")).where(F.col("c") >= min_shared).select("src", "dst")
    vertices = load(spark, sf_dir, "part").select(F.col("p_partkey").cast("long").alias("id"), F.expr(label).cast("string").alias("label"), "p_size", "p_brand")
    return undirected(vertices, pairs, "CO")


def near(a: np.ndarray, b: np.ndarray, threshold: float) -> np.ndarray:
    """Which rows of a have which rows of b at a cosine at or above the threshold."""
    cos = (a @ b.T) / np.maximum(np.linalg.norm(a, axis=1)[:, None] * np.linalg.norm(b, axis=1)[None, :], 1e-300)
    return cos >= threshold


def similar_triangles(spark: SparkSession, sf_dir: str, threshold: float = 0.3, block: int = BLOCK) -> DataFrame:
    """The triangles a, b, c of `similar`, made from the vectors without its arcs."""
    rows = load(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("long").alias("id"), F.col("embedding").alias("v")).where("id IS NOT NULL AND v IS NOT NULL")
    return triangles(rows, lambda a, b: near(a, b, threshold), block)


def similar(spark: SparkSession, sf_dir: str, threshold: float = 0.3, block: int = 2048) -> PropertyGraph:
    """Vectors of cosine at or above the threshold: exact, block against block of bounded size."""
    rows = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("label").cast("string").alias("label"), F.transform("embedding", lambda x: x.cast("double")).alias("v")).where("id IS NOT NULL AND v IS NOT NULL")
    n = max(1, -(-rows.count() // block))
    mine = F.pmod(F.xxhash64("id"), F.lit(n))
    left = rows.select(F.col("id").alias("id1"), F.col("v").alias("v1"), mine.alias("i")).withColumn("j", F.explode(F.sequence(F.col("i"), F.lit(n - 1).cast("long"))))
    right = rows.select(F.col("id").alias("id2"), F.col("v").alias("v2"), mine.alias("j")).withColumn("i", F.explode(F.sequence(F.lit(0).cast("long"), F.col("j"))))

    def pair(x: pd.DataFrame, y: pd.DataFrame) -> pd.DataFrame:
        if not len(x) or not len(y):
            return pd.DataFrame({"src": pd.Series(dtype="int64"), "dst": pd.Series(dtype="int64")})
        a, b = np.stack(x["v1"].to_numpy()), np.stack(y["v2"].to_numpy())
        r, c = np.nonzero(near(a, b, threshold))
        s, d = x["id1"].to_numpy()[r], y["id2"].to_numpy()[c]
        return pd.DataFrame({"src": np.minimum(s, d)[s != d], "dst": np.maximum(s, d)[s != d]})

    key = lambda df, *cols: df.select(F.concat_ws(":", "i", "j").alias("k"), *cols).groupBy("k")
    pairs = key(left, "id1", "v1").cogroup(key(right, "id2", "v2")).applyInPandas(pair, "src long, dst long").distinct()
    return undirected(rows.select("id", "label"), pairs, "NEAR")


def document_lines(spark: SparkSession, sf_dir: str, min_chars: int = 30) -> DataFrame:
    """doc, line: the distinct longer lines of each document; the bipartite form, safe for hot lines."""
    d = load(spark, sf_dir, "documents").select(F.col("doc_id").alias("doc"), F.explode(F.split("text", "\n")).alias("line"))
    return d.where(F.length("line") > min_chars).distinct()


def shared_lines(spark: SparkSession, sf_dir: str, min_chars: int = 30, label: str = "lang") -> PropertyGraph:
    """Documents that share a line. Lines meet by hash; the pairs of a hot line grow with its square."""
    lines = document_lines(spark, sf_dir, min_chars).select("doc", F.xxhash64("line").alias("h"), "line")
    shared = lines.join(lines.groupBy("h").agg(F.count("*").alias("c")).where("c > 1").select("h"), "h")
    pairs = shared.select("h", "line", F.col("doc").alias("src")).join(shared.select("h", "line", F.col("doc").alias("dst")), ["h", "line"]).where("src < dst").select("src", "dst").distinct()
    return undirected(load(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), F.col(label).alias("label")), pairs, "LINE")


def line_cover(spark: SparkSession, sf_dir: str, min_chars: int = 30, hashes: int = 200_000) -> Cover:
    """The same links as `shared_lines`, with the pairs of frequent lines left as sets: nothing grows with
    the square of a line's documents. Texts travel only for lines whose hash is in several documents;
    up to so many hashes are broadcast."""
    d = load(spark, sf_dir, "documents").where("doc_id IS NOT NULL").select(F.col("doc_id").alias("id"), F.explode(F.split("text", "\n")).alias("key")).where(F.length("key") > min_chars)
    d = d.withColumn("h", F.xxhash64("key"))
    often = written(d.groupBy("h").agg(F.min("id").alias("a"), F.max("id").alias("b")).where("a <> b").select("h"), "hashes")
    some = F.broadcast(often) if often.count() <= hashes else often.hint("merge")
    return cover(written(d.join(some, "h", "left_semi").select("id", "key").distinct(), "lines"))


def contains(spark: SparkSession, sf_dir: str, run: int = 5) -> PropertyGraph:
    """Documents that contain a benchmark item's text.

    The inner words of an item stand in a document as whole words between single blanks, so item and
    document meet by a hash of a run of them (`run` words, of shorter items one word), and the texts
    are compared where they meet. Items without an inner word meet every document.
    """
    items = load(spark, sf_dir, "benchmark").select(F.col("item_id").alias("item"), F.col("text").alias("needle")).where("needle IS NOT NULL")
    docs = load(spark, sf_dir, "documents").select("doc_id", "text")
    inner = F.size(F.split("needle", " ")) - 2
    sized = items.withColumn("w", F.split("needle", " ")).withColumn("n", F.when(inner >= run, F.lit(run)).when(inner >= 1, F.lit(1)).otherwise(F.lit(0)))
    found = []
    for n in (run, 1):
        anchors = sized.where(F.col("n") == n).select("item", "needle", F.xxhash64(F.array_join(F.slice("w", 2, n), " ")).alias("h"))
        word = F.split("text", " ")
        runs = docs.where(F.size(word) >= n + 2).select("doc_id", word.alias("w"))
        runs = runs.select("doc_id", F.explode(F.transform(F.sequence(F.lit(2), F.size("w") - n), lambda k: F.xxhash64(F.array_join(F.slice("w", k, n), " ")))).alias("h")).distinct()
        met = runs.join(anchors, "h").select("doc_id", "item", "needle").distinct()
        found.append(met.join(docs, "doc_id").where(F.contains("text", "needle")).select("doc_id", "item"))
    short = sized.where("n = 0").select("item", "needle")
    found.append(docs.join(short, F.contains("text", "needle")).select("doc_id", "item"))
    hits = reduce(DataFrame.unionByName, found).select(F.col("doc_id").alias("src"), (F.col("item") + TAG).alias("dst")).distinct()
    vertices = docs.select(F.col("doc_id").alias("id"), F.lit("document").alias("label")).unionByName(items.select((F.col("item") + TAG).alias("id"), F.lit("item").alias("label")))
    return PropertyGraph(vertices, hits.withColumn("elabel", F.lit("HOLDS")), directed=True)


def links(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Pages and the tokens of their hrefs, numbered in a table of their own, so no two share an id."""
    hits = load(spark, sf_dir, "pages").select(F.col("page_id").alias("src"), F.explode(F.expr(r"regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)")).alias("href")).distinct()
    tokens = written(hits.select("href").distinct().withColumn("dst", F.monotonically_increasing_id() + F.lit(TAG)), "tokens")
    vertices = load(spark, sf_dir, "pages").select(F.col("page_id").alias("id"), F.lit("page").alias("label")).unionByName(tokens.select(F.col("dst").alias("id"), F.lit("href").alias("label")))
    return PropertyGraph(vertices, hits.join(tokens, "href").select("src", "dst", F.lit("LINKS").alias("elabel")), directed=True)


def events(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Users and the keys of their events; the edge label is the event type."""
    e = load(spark, sf_dir, "events").select(F.col("user_id").alias("src"), (F.get_json_object("props", "$.k").cast("long") + TAG).alias("dst"), F.col("event_type").alias("elabel")).where("src IS NOT NULL AND dst IS NOT NULL").distinct()
    vertices = e.select(F.col("src").alias("id"), F.lit("user").alias("label")).distinct().unionByName(e.select(F.col("dst").alias("id"), F.lit("key").alias("label")).distinct())
    return PropertyGraph(vertices, e, directed=True)


#: No conversation has more turns than this.
TURNS = 1_000_000_000


def turns(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Conversation turns, each linked to the next one of its conversation; label is the role."""
    t = load(spark, sf_dir, "conversations").select((F.col("conv_id") * TURNS + F.col("turn")).alias("id"), F.col("role").alias("label"), "conv_id", "turn")
    nxt = F.lead("id").over(Window.partitionBy("conv_id").orderBy("turn"))
    return PropertyGraph(t, t.select(F.col("id").alias("src"), nxt.alias("dst"), F.lit("NEXT").alias("elabel")).where("dst IS NOT NULL"), directed=True)


#: The same graphs in DuckDB's SQL: vertices (id, label) and arcs (src, dst, elabel).
_T = {k: f"{v * TAG}" for k, v in TAGS.items()}
TRADE_ARCS = [
    (e, f"SELECT DISTINCT {a}::BIGINT + {_T[ends[0]]} AS src, {b}::BIGINT + {_T[ends[1]]} AS dst, '{e}' AS elabel FROM {t}")
    for e, (t, a, b, ends) in TRADE_KINDS.items()
]
GRAPH_SQL = {
    "trade": (
        " UNION ALL ".join(f"SELECT {c}::BIGINT + {_T[k]} AS id, '{k}' AS label FROM {k}" for k, c in (("region", "r_regionkey"), ("nation", "n_nationkey"), ("customer", "c_custkey"), ("supplier", "s_suppkey"), ("part", "p_partkey"), ("orders", "o_orderkey"))),
        " UNION ALL ".join(arcs for _, arcs in TRADE_ARCS),
    ),
    "sim": ("SELECT vec_id AS id, CAST(label AS VARCHAR) AS label FROM embeddings", "SELECT a.vec_id AS src, b.vec_id AS dst, 'NEAR' AS elabel FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id AND list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) >= 0.3"),
    "doc": ("SELECT doc_id AS id, lang AS label FROM documents", "SELECT DISTINCT a.d AS src, b.d AS dst, 'LINE' AS elabel FROM (SELECT DISTINCT doc_id AS d, unnest(string_split(text, chr(10))) AS l FROM documents) a JOIN (SELECT DISTINCT doc_id AS d, unnest(string_split(text, chr(10))) AS l FROM documents) b ON a.l = b.l AND a.d <> b.d WHERE length(a.l) > 30"),
    "leak": (f"SELECT doc_id AS id, 'document' AS label FROM documents UNION ALL SELECT item_id + {TAG}, 'item' FROM benchmark", f"SELECT DISTINCT d.doc_id AS src, b.item_id + {TAG} AS dst, 'HOLDS' AS elabel FROM documents d JOIN benchmark b ON contains(d.text, b.text)"),
    "event": (f"SELECT DISTINCT user_id AS id, 'user' AS label FROM events UNION ALL SELECT DISTINCT CAST(props ->> '$.k' AS BIGINT) + {TAG}, 'key' FROM events", f"SELECT DISTINCT user_id AS src, CAST(props ->> '$.k' AS BIGINT) + {TAG} AS dst, event_type AS elabel FROM events"),
    "conv": (f"SELECT conv_id * {TURNS} + turn AS id, role AS label FROM conversations", f"SELECT * FROM (SELECT conv_id * {TURNS} + turn AS src, lead(conv_id * {TURNS} + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS dst, 'NEXT' AS elabel FROM conversations) WHERE dst IS NOT NULL"),
}
for _k in (1, 2):
    _pairs = f"SELECT a.p AS src, b.p AS dst, 'CO' AS elabel FROM (SELECT DISTINCT l_orderkey AS o, l_partkey AS p FROM lineitem) a JOIN (SELECT DISTINCT l_orderkey AS o, l_partkey AS p FROM lineitem) b ON a.o = b.o AND a.p <> b.p GROUP BY a.p, b.p HAVING count(*) >= {_k}"
    GRAPH_SQL["copart" if _k == 1 else "copart2"] = ("SELECT p_partkey AS id, p_type AS label, p_size, p_brand FROM part", _pairs)

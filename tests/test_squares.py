"""Squares with twin corners, counted by paths, against brute force and the search."""

import random
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from bundlegraph.model import PropertyGraph
from bundlegraph.operators import squares as S
from bundlegraph.operators.match import match
from bundlegraph.plans.pattern import parse
from bundlegraph.queries import QUERIES
from bundlegraph.sources import graphs as G
from bundlegraph.workload import SOCIAL, social

SMALLEST = "/root/testdata/sf0.001"


def brute(lines, others):
    met = Counter((o, s) for o, p in set(lines) for s, x in set(others) if x == p)
    return sum(c * (c - 1) for c in met.values())


def made(seed, far=1):
    """A hub with many vias, vias without others, pairs that are there twice."""
    rng = random.Random(seed)
    lines = [(rng.randrange(12) * far, rng.randrange(15) * far) for _ in range(60)] + [(5 * far, p * far) for p in range(15)]
    others = [(rng.randrange(9) * far, rng.randrange(3, 18) * far) for _ in range(70)]
    return lines + lines[:9], others + others[:9]


@pytest.mark.parametrize("paths,table,far", [(2_000_000, 1 << 24, 1), (1, 0, 1), (7, 0, -(1 << 40)), (40, 1 << 24, 1 << 30)])
def test_lots_and_hubs_of_many_paths(monkeypatch, paths, table, far):
    monkeypatch.setattr(S, "PATHS", paths), monkeypatch.setattr(S, "TABLE", table)
    lines, others = made(paths, far)
    blobs = [[S.packed(*np.array(part, dtype=np.int64).T) for part in (df[:25], df[25:])] for df in (lines, others)]
    assert sorted({*zip(*(x.tolist() for x in S.unpacked(blobs[0][0])))}) == sorted(set(lines[:25]))
    assert S.squares_of(*blobs) == brute(lines, others) > 0
    assert S.squares_of([], blobs[1]) == S.squares_of(blobs[0], []) == 0


@pytest.mark.parametrize("arcs", [6, 4_000_000])
def test_blocks_against_blocks(spark, monkeypatch, arcs):
    monkeypatch.setattr(S, "ARCS", arcs)
    lines, others = made(3)
    rows = [(o, p, "HAS") for o, p in lines] + [(s, p, "GIVES") for s, p in others] + [(None, 1, "HAS"), (1, None, "GIVES")]
    g = PropertyGraph(None, spark.createDataFrame(rows, "src long, dst long, elabel string"), directed=True, types={"HAS": ("o", "p"), "GIVES": ("s", "p")})
    q = parse("(a:p)<-[:HAS]-(o:o)-[:HAS]->(b:p)<-[:GIVES]-(s:s)-[:GIVES]->(a)", directed=True)
    assert S.squares(g, S.square_of(g, q)).first().n == brute(lines, others)
    empty = PropertyGraph(None, g.edges.where("elabel = 'HAS'"), directed=True, types=g.types)
    assert S.squares(empty, S.square_of(g, q)).first().n == 0


def test_which_queries_are_such_squares(spark):
    g = G.trade(spark, SMALLEST)
    assert [n for n in SOCIAL if S.square_of(g, social(n))] == ["s3"]
    back = parse("(o:orders)-[:CONTAINS]->(p:part)<-[:SUPPLIES]-(s:supplier)-[:SUPPLIES]->(x:part), (y:orders)-[:CONTAINS]->(x)", directed=True)
    assert S.square_of(g, back) is None
    ordered = parse(f"{SOCIAL['s3']}; p < x", directed=True)
    assert S.square_of(g, ordered) is None


def test_s3_moves_no_paths(spark):
    """The query joined parts with all their suppliers and wrote a row for each."""
    df = QUERIES["s3"](spark, SMALLEST)
    assert "Join" not in df._jdf.queryExecution().executedPlan().toString()
    assert df.first().n == match(G.trade(spark, SMALLEST), social("s3")).count().first().n == 214_898


def test_arcs_that_are_there_twice_count_once(spark, tmp_path):
    for t in G.TRADE_TABLES:
        df = G.load(spark, SMALLEST, t)
        (df.unionByName(df) if t == "lineitem" else df).write.parquet(f"{tmp_path}/{t}.parquet")
    assert QUERIES["s3"](spark, str(tmp_path)).select(F.col("n")).first().n == 214_898

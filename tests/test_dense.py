"""Triangles of near vectors, block against block against block, against brute force."""

import itertools

import numpy as np
import pytest

from bundlegraph.operators import dense
from bundlegraph.queries import QUERIES
from bundlegraph.sources import graphs as G


def brute(ids, v, threshold=0.3):
    cos = G.near(v, v, threshold)
    near = {(a, b) for (a, x), (b, y) in itertools.product(zip(ids, range(len(ids))), repeat=2) if a != b and cos[x, y]}
    names = sorted(set(ids))
    return sorted(t for t in itertools.permutations(names, 3) if {(t[0], t[1]), (t[1], t[2]), (t[0], t[2])} <= near)


def vectors(spark, path, ids, v):
    rows = [(i, [float(c) for c in x], 0) for i, x in zip(ids, v)] + [(None, [1.0] * v.shape[1], 0), (10_000, None, 0)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").write.parquet(f"{path}/embeddings.parquet")


@pytest.mark.parametrize("rows,pairs", [(256, 1 << 21), (3, 4), (2, 1)])
def test_lots_of_rows_and_pairs(monkeypatch, rows, pairs):
    """In one block: each triangle once, its corners in order; id 6 is there twice."""
    monkeypatch.setattr(dense, "ROWS", rows), monkeypatch.setattr(dense, "PAIRS", pairs)
    v = np.random.default_rng(rows).normal(size=(30, 5))
    ids = np.array([*range(29), 6])
    one = dense.Block(ids, v)
    found = [(x, y, z) for a, b, n, c in dense.corners(one, one, one, lambda x, y: G.near(x, y, 0.3)) for x, y, z in zip(np.repeat(a, n), np.repeat(b, n), c)]
    assert sorted(found) == [t for t in brute(ids.tolist(), v) if t[0] < t[1] < t[2]] and found


@pytest.mark.parametrize("block", [8192, 17, 5])
def test_every_triangle_once_in_each_order(spark, tmp_path, block):
    """One block and many; copies of one vector, a zero vector, and an id that is there twice."""
    v = np.random.default_rng(block).normal(size=(40, 6)).astype(np.float32).astype(float)
    v[30:36], v[36] = v[30], 0
    ids = [3 * k for k in range(39)] + [6]
    vectors(spark, tmp_path, ids, v)
    got = sorted(tuple(r) for r in G.similar_triangles(spark, str(tmp_path), block=block).collect())
    assert got == brute(ids, v) and got


def test_no_path_of_two_arcs_is_moved(spark, tmp_path):
    """The query joined arcs with arcs, which wrote far more rows than the answer has."""
    vectors(spark, tmp_path, list(range(30)), np.ones((30, 3)))
    df = QUERIES["sim_triangle"](spark, str(tmp_path))
    assert "Join" not in df._jdf.queryExecution().executedPlan().toString()
    assert df.columns == ["a", "b", "c"] and df.distinct().count() == 30 * 29 * 28


def test_no_vector_no_triangle(spark, tmp_path):
    vectors(spark, tmp_path, [], np.ones((0, 3)))
    assert QUERIES["sim_triangle"](spark, str(tmp_path)).collect() == []


def test_vectors_of_different_length_are_named(spark, tmp_path):
    spark.createDataFrame([(1, [1.0], 0), (2, [1.0, 2.0], 0)], "vec_id long, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    with pytest.raises(Exception, match="differ in length"):
        QUERIES["sim_triangle"](spark, str(tmp_path)).collect()

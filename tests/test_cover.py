"""Graphs of sets whose members are all linked, against brute force."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from bundlegraph.operators import cover as C


def brute(sets):
    arcs = {(a, b) for s in sets.values() for a in s for b in s if a != b}
    ids = {a for a, _ in arcs}
    near = {a: {b for x, b in arcs if x == a} for a in ids}
    return arcs, sum(len(near[a] & near[b]) for a, b in arcs)


@pytest.mark.parametrize("seed,small,block", [(1, 3, 512), (2, 2, 2), (3, 1, 3), (4, 50, 512)])
def test_large_sets_stay_sets(spark, monkeypatch, seed, small, block):
    """Large sets alone, small ones alone, and triangles with none, one, two and three arcs."""
    monkeypatch.setattr(C, "BLOCK", block)
    rng = random.Random(seed)
    sets = {f"s{k}": set(rng.sample(range(40), rng.choice([1, 2, 2, 2, 3, 3, 5, 9]))) for k in range(22)} | {"twin": {1, 2, 3, 4, 5}, "twin2": {1, 2, 3, 4, 5}}
    df = spark.createDataFrame([(v, k) for k, s in sets.items() for v in s], "id long, key string")
    got, (arcs, triangles) = C.cover(df, small).store(), brute(sets)
    assert tuple(got.summary(31, 13).first()) == (len(arcs), sum((31 * a + b) % 13 for a, b in arcs))
    assert got.triangles().first()[0] == triangles
    assert got.arcs.count() <= small * df.count()


def test_a_frequent_set_makes_no_pairs(spark):
    """A set of 3000 members has 9 million arcs and 27 thousand million triangles; none is made."""
    n = 3000
    got = C.cover(spark.range(n).withColumn("key", F.lit("hot"))).store()
    assert got.arcs.count() == 0 and got.members.count() == n
    assert got.summary(31, 1009).first().n == n * (n - 1)
    assert got.triangles().first()[0] == n * (n - 1) * (n - 2)


def test_no_set_no_arc(spark):
    got = C.cover(spark.createDataFrame([(1, "a"), (2, "b")], "id long, key string")).store()
    assert got.summary(31, 1009).collect() == [] and got.triangles().first()[0] == 0


def test_frequent_lines_of_documents(spark, tmp_path):
    """The builder gives the arcs of the plain join over lines; short lines, nulls and repeats in a text do not count."""
    from bundlegraph.sources import graphs as G

    hot, pair = "a line that is in very many documents", "a line that is in two documents only"
    texts = [(k, f"{hot}\n{hot}\nshort") for k in range(100)] + [(100, f"{pair}\nx"), (101, f"y\n{pair}"), (102, "short\nx"), (103, None), (99, f"{pair}\n{hot}")]
    texts.remove((99, f"{hot}\n{hot}\nshort"))
    spark.createDataFrame(texts, "doc_id long, text string").withColumn("lang", F.lit("en")).write.parquet(str(tmp_path / "documents.parquet"))
    plain = G.shared_lines(spark, str(tmp_path)).edges
    want = plain.agg(F.count("*"), F.sum(F.pmod(F.col("src") * 31 + F.col("dst"), F.lit(1009)))).first()
    for hashes in (200_000, 0):
        got = G.line_cover(spark, str(tmp_path), hashes=hashes).store()
        assert tuple(got.summary(31, 1009).first()) == tuple(want) and want[0] == 100 * 99 + 6
        assert got.triangles().first()[0] == 100 * 99 * 98 + 6

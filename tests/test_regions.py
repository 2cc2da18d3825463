"""The work of the depth-first search where its index is too large to be broadcast."""

import random

import pytest

from bundlegraph import experiments as X
from bundlegraph.model import MatchSpec, PropertyGraph
from bundlegraph.workload import shape


@pytest.mark.parametrize("colouring", ["all_pinned", "risk"])
def test_regions_count_the_same_work(spark, colouring):
    rng = random.Random(5)
    label = {v: rng.choice("AB") for v in range(24)}
    pairs = [(a, b) for a in range(24) for b in range(a) if rng.random() < 0.25]
    vertices = spark.createDataFrame(list(label.items()), "id long, label string")
    arcs = spark.createDataFrame([(a, b, "e") for x, y in pairs for a, b in ((x, y), (y, x))], "src long, dst long, elabel string")
    g = PropertyGraph(vertices, arcs).store()
    queries = {"star": shape("star3", {"a": "A", "b": "B"}), "house": shape("house", {"a": "A", "c": "B"})}
    spec = MatchSpec(engine="kernel", colouring=colouring)
    specs = {"reuse": spec, "no_failing": spec.but(reuse=None, prune_failing=False)}
    want = {tuple(r) for r in X.search_work(g, queries, specs).where("n > 0").select("method", "query", "name", "n").collect()}
    small = {k: s.but(kernel_arcs=0) for k, s in specs.items()}
    got = {tuple(r) for r in X.search_work(g, queries, small).where("n > 0").select("method", "query", "name", "n").collect()}
    assert got == want and {r[2] for r in want} >= {"nodes", "computed"}

"""Walks are made once for each size, and scan the arcs without dealing them anew."""

from bundlegraph import experiments as X
from bundlegraph import workload
from bundlegraph.model import PropertyGraph
from bundlegraph.operators.baselines import sql_join
from bundlegraph.workload import shape


def test_walks_are_shared_and_stored_arcs_stay(spark, monkeypatch):
    pairs = [(a, b) for a in range(12) for b in range(12) if a != b and (a + b) % 3]
    g = PropertyGraph(spark.createDataFrame([(v, "A") for v in range(12)], "id long, label string"), spark.createDataFrame([(a, b, "e") for a, b in pairs], "src long, dst long, elabel string")).store()
    made, walked = [], workload._walked
    monkeypatch.setattr(workload, "_walked", lambda *a: made.append(a[1:]) or walked(*a))
    found = X.query_set(g, (5,), 1)
    assert len(made) == 1 and found
    assert all(q.n == 5 for q in found.values())
    text = sql_join(g, shape("triangle", {"a": "A", "b": "A", "c": "A"}))._jdf.queryExecution().optimizedPlan().toString()
    assert text.count("Aggregate [src") == 0 and text.count("Aggregate [dst") == 0

"""The level-wise engine, sources, streaming and SQL surface on small graphs."""

import itertools
import random
from collections import Counter

import pytest
from pyspark.sql import functions as F

from bundlegraph.model import MatchSpec, PropertyGraph, QueryGraph
from bundlegraph.operators import baselines, expand
from bundlegraph.operators.batched import batched
from bundlegraph.operators.filters import filter_candidates
from bundlegraph.operators.match import match, prepare
from bundlegraph.plans import colouring, ordering
from bundlegraph.plans.analysis import back_sets, closed, dependency_sets, make_plan
from bundlegraph.plans.pattern import parse
from bundlegraph.sources.textgraph import read_edges, read_graph, write_graph
from bundlegraph.functions import scratch
from bundlegraph.functions.deadline import within
from bundlegraph.operators.levels import FEW
from bundlegraph.sqlapi import match_sql, register, register_graph
from bundlegraph.streaming import matching as S
from bundlegraph.workload import SHAPES, SOCIAL, random_walk_queries, shape, social


def graph(spark, labels, pairs, elabel="e", directed=False):
    v = spark.createDataFrame([(i, lab) for i, lab in labels.items()], "id long, label string")
    arcs = [(a, b, elabel) for a, b in pairs] + ([] if directed else [(b, a, elabel) for a, b in pairs])
    return PropertyGraph(v, spark.createDataFrame(arcs, "src long, dst long, elabel string"), directed)


def rows(df):
    return sorted(tuple(r) for r in df.collect())


# fixed values: the toy graph and its eight matches
TOY_LABELS = dict(enumerate("ABCCDDDEEFFGG"))
TOY_PAIRS = [(0, 1), (0, 2), (0, 3), (2, 4), (2, 5), (2, 6), (3, 6), (0, 7), (0, 8), (1, 7), (1, 8), (4, 9), (5, 9), (5, 10), (6, 10), (9, 12), (10, 11), (10, 12), (7, 12), (8, 11)]
TOY_QUERY = QueryGraph(tuple(f"u{i}" for i in range(7)), tuple("ABCDEFG"), tuple((a, b, None) for a, b in ((0, 1), (0, 2), (2, 3), (0, 4), (1, 4), (3, 5), (4, 6), (5, 6))))
TOY_MATCHES = [(0, 1, 2, 4, 7, 9, 12), (0, 1, 2, 5, 7, 9, 12), (0, 1, 2, 5, 7, 10, 12), (0, 1, 2, 5, 8, 10, 11), (0, 1, 2, 6, 7, 10, 12), (0, 1, 2, 6, 8, 10, 11), (0, 1, 3, 6, 7, 10, 12), (0, 1, 3, 6, 8, 10, 11)]


def test_toy_graph(spark):
    g = graph(spark, TOY_LABELS, TOY_PAIRS).store()
    spec = MatchSpec(filters=("label",), order=tuple(range(7)), colouring=(False, False, False, True, False, False, True), prune_dominated=False)
    r = match(g, TOY_QUERY, spec)
    assert sorted((a, b, c, tuple(d)) for a, b, c, d in r.levels[3].collect()) == [(0, 1, 2, (4, 5, 6)), (0, 1, 3, (6,))]
    assert (r.plan.depends[4], r.plan.anchor[4], r.plan.reusable[4]) == (frozenset({0, 1}), 1, True)
    assert (r.plan.case(3), r.plan.case(5), r.plan.back_pinned(5)) == (2, 3, [])
    assert rows(r.flat()) == TOY_MATCHES
    for engine in ("levels", "kernel"):
        for c in ("risk", "all_bundled", "tail_only", "all_pinned"):
            assert rows(match(g, TOY_QUERY, MatchSpec(engine=engine, colouring=c)).flat()) == TOY_MATCHES


def brute(q, label, arcs, iso=True):
    opts = [[v for v in sorted(label) if q.labels[u] in (None, label[v])] for u in range(q.n)]
    return sorted(m for m in itertools.product(*opts) if (not iso or len(set(m)) == q.n) and all((m[a], m[b]) in arcs for a, b, _ in q.edges))


@pytest.mark.parametrize("seed", range(3))
def test_levels_equal_brute_force(spark, seed):
    rng = random.Random(seed)
    label = {v: rng.choice("AB") for v in range(9)}
    pairs = [(a, b) for a in range(9) for b in range(a) if rng.random() < 0.45]
    arcs = {x for a, b in pairs for x in ((a, b), (b, a))}
    g = graph(spark, label, pairs).store()
    q = shape(["diamond", "path4", "house"][seed], {"a": "A", "c": "B"} if seed else {"a": "A"})
    want, hom = brute(q, label, arcs), brute(q, label, arcs, False)
    for spec in (MatchSpec(), MatchSpec(colouring="all_bundled", reuse="dep"), MatchSpec(colouring=tuple(rng.random() < 0.6 for _ in range(q.n)), injectivity="late", reuse=None), MatchSpec(colouring="risk_smoothed", split_case3=True)):
        r = match(g, q, spec)
        assert rows(r.flat()) == want
        assert r.count().first()[0] == len(want)
    assert rows(match(g, q, MatchSpec(semantics="hom", colouring="tail_only")).flat()) == hom
    induced = [m for m in want if all((m[a], m[b]) not in arcs for a in range(q.n) for b in range(a) if (b, a) not in q.links())]
    assert rows(match(g, q, MatchSpec(semantics="induced")).flat()) == induced


def test_degenerate_queries(spark):
    g = graph(spark, {1: "A", 2: "B", 3: "B", 4: None}, [(1, 2), (1, 3), (1, 2), (4, 4)]).store()
    one = QueryGraph.of({"x": "B"}, [])
    assert rows(match(g, one).flat()) == [(2,), (3,)]
    assert rows(match(g, parse("(x:A)-(y:B)", directed=False)).flat()) == [(1, 2), (1, 3)]
    none = match(g, parse("(x:C)-(y:B)", directed=False)).flat()
    assert none.columns == ["x", "y"] and none.count() == 0
    assert rows(match(g, QueryGraph.of({"x": "B", "y": "B"}, [])).flat()) == [(2, 3), (3, 2)]
    assert rows(match(g, QueryGraph.of({"x": None}, [("x", "x")])).flat()) == [(4,)]
    star = parse("(r:A)-(x:B), (r)-(y:B), (r)-(z:B)", directed=False)
    clash = MatchSpec(filters=("label",), order=(0, 1, 2, 3), colouring=(False, True, True, True), prune_dominated=False)
    assert match(g, star, clash).count().first()[0] == 0 and match(g, star, clash).flat().count() == 0
    empty = graph(spark, {1: "A"}, [(1, 1)])
    assert match(empty, parse("(x:A)-(y:A)", directed=False)).flat().count() == 0
    assert match(g, parse("(x:A)-(y:B)", directed=False), MatchSpec(limit=1)).flat().count() == 1


def test_case4_takes_both_ways(spark):
    label = {0: "R", 1: "R", **{i: "X" for i in range(2, 8)}, **{i: "Y" for i in range(10, 16)}}
    pairs = [(0, 2), *[(2, y) for y in range(10, 16)], *[(1, x) for x in range(3, 8)], *[(x, 10) for x in range(3, 8)]]
    g = graph(spark, label, pairs).store()
    q = parse("(r:R)-(x:X)-(y:Y)", directed=False)
    spec = MatchSpec(filters=("label",), order=(0, 1, 2), colouring=(False, True, True))
    r = match(g, q, spec)
    images = [(len(a.q1), len(a.q2)) for a in r.packed.collect()]
    assert (1, 6) in images and (5, 1) in images
    arcs = {x for a, b in pairs for x in ((a, b), (b, a))}
    assert rows(r.flat()) == brute(q, label, arcs)


def test_counts_by_partitions(spark):
    assert len(expand.partitions([1, 2, 3, 4])) == 15
    df = spark.createDataFrame([([1, 2, 3], [2, 3], [3, 4, 5])], "q0 array<long>, q1 array<long>, q2 array<long>")
    want = sum(len(set(m)) == 3 for m in itertools.product([1, 2, 3], [2, 3], [3, 4, 5]))
    assert int(df.select(expand.distinct_choices([0, 1, 2])).first()[0]) == want


def test_plans_by_hand():
    q = shape("path4")
    assert ordering.by_candidate_ratio(q, [10, 4, 6, 1]) == (3, 2, 1, 0)
    back = back_sets(q, (0, 1, 2, 3))
    assert back == [(), (0,), (1,), (2,)]
    assert colouring.by_risk(q, (0, 1, 2, 3), [5, 5, 5, 5]) == (False, True, False, True)
    assert colouring.tail_only(q, (0, 1, 2, 3), [5] * 4) == (False, False, False, True)
    cover = colouring.vertex_cover(q, (0, 1, 2, 3), [5] * 4)
    assert not any(a and b for a, b in zip(cover, cover[1:]))
    assert dependency_sets(back, (False, True, False, False))[2] == frozenset({0, 1})
    assert closed({1}, 3, back, (False, True, False, False)) == frozenset({0, 1, 2})
    star = shape("star3", {"a": "A", "b": "B", "c": "B", "d": "B"})
    plan = make_plan(star, [1, 3, 3, 3], MatchSpec(order=(0, 1, 2, 3)), lambda i, j: True)
    assert plan.need == (1, 3, 2, 1)
    assert make_plan(star, [1, 3, 3, 3], MatchSpec(order=(0, 1, 2, 3)), lambda i, j: False).need == (1, 1, 1, 1)


def test_pattern_grammar():
    q = parse("(a:part {p_size > 10})-[:CONTAINS]->(b:orders), (b)<-[:X]-(c); a < c")
    assert q.names == ("a", "b", "c") and q.labels == ("part", "orders", None) and q.directed
    assert q.edges == ((0, 1, "CONTAINS"), (2, 1, "X")) and q.where[0] == "p_size > 10" and q.cross == ((0, "<", 2),)
    assert QueryGraph.from_json(q.to_json()) == q
    for bad in ("(a", "(a)-", "(a:x)-(a:y)", "(a) (b)", "(a)-(b); a ~ b"):
        with pytest.raises(ValueError):
            parse(bad)
    assert all(parse(t).n >= 2 for t in SHAPES.values()) and all(social(n).directed for n in SOCIAL)


def test_baselines_agree(spark):
    rng = random.Random(9)
    label = {v: rng.choice("AB") for v in range(10)}
    pairs = [(a, b) for a in range(10) for b in range(a) if rng.random() < 0.4]
    g = graph(spark, label, pairs).store()
    q = shape("cycle4", {"a": "A"})
    want = brute(q, label, {x for a, b in pairs for x in ((a, b), (b, a))})
    for f in (baselines.dynamic_failing_set, baselines.dynamic_equivalence, baselines.guarded, baselines.neighbour_classes, baselines.sql_join):
        assert rows(f(g, q)) == want, f
    for f in (baselines.static_leaf_grouping, baselines.batch_homomorphism, baselines.backtracking, baselines.level_by_level, baselines.vertex_cover):
        assert rows(f(g, q).flat()) == want, f
    got, facts = batched(g, q, MatchSpec(batches=3, limit=5))
    assert got.count() == min(5, len(want)) and set(rows(got)) <= set(want)
    assert batched(g, q, MatchSpec(batches=3, timeout_s=0.0))[1]["timed_out"]


def test_directed_and_edge_labels(spark):
    v = spark.createDataFrame([(i, "N") for i in range(5)], "id long, label string")
    arcs = [(0, 1, "x"), (1, 0, "y"), (1, 2, "x"), (2, 0, "x"), (3, 4, "x"), (4, 3, "x"), (0, 1, "y")]
    g = PropertyGraph(v, spark.createDataFrame(arcs, "src long, dst long, elabel string"), True)
    assert rows(match_sql(g, "(a)-[:x]->(b), (b)-[:y]->(a)")) == [(0, 1)]
    assert rows(match_sql(g, "(a)-[:x]->(b)-[:x]->(c)-[:x]->(a)")) == [(0, 1, 2), (1, 2, 0), (2, 0, 1)]
    assert rows(match_sql(g, "(a)-[:x]->(b)-[:x]->(a)")) == [(3, 4), (4, 3)]
    assert rows(match_sql(g, "(a)-[:x]->(b), (a)-[:y]->(b)")) == [(0, 1)]


def test_filters_keep_every_image(spark):
    g = graph(spark, TOY_LABELS, TOY_PAIRS).store()
    for spec in (MatchSpec(filters=("label",)), MatchSpec(), MatchSpec(arc_passes=3)):
        cand = [{r.id for r in c.collect()} for c in filter_candidates(g, TOY_QUERY, spec)]
        assert all(m[u] in cand[u] for m in TOY_MATCHES for u in range(7))


def test_random_walks_have_matches(spark):
    g = graph(spark, TOY_LABELS, TOY_PAIRS).store()
    found = random_walk_queries(g, 4, "any", 4, seed=1)
    assert found and all(q.n == 4 and len(q.components()) == 1 for q in found)
    assert all(match(g, q).flat().count() > 0 for q in found[:2])
    assert random_walk_queries(g, 4, "any", 4, seed=1) == found


def test_plans_have_no_cartesian_product(spark):
    g = graph(spark, TOY_LABELS, TOY_PAIRS).store()
    r = match(g, TOY_QUERY)
    text = r.flat()._jdf.queryExecution().toString()
    assert "CartesianProduct" not in text and "BroadcastNestedLoop" not in text


def test_text_graph_round_trip(spark, tmp_path):
    g = graph(spark, {1: "A", 2: None, 3: "B c"}, [(1, 2), (2, 3)], elabel="k l")
    g = PropertyGraph(g.vertices.withColumn("label", F.regexp_replace("label", " ", "_")), g.edges.withColumn("elabel", F.lit("kl")))
    write_graph(g, str(tmp_path / "g"))
    back = read_graph(spark, str(tmp_path / "g"))
    assert set(back.vertices.collect()) == set(g.vertices.collect()) and rows(back.edges) == rows(g.edges)
    g.edges.write.csv(str(tmp_path / "csv"))
    assert rows(read_edges(spark, str(tmp_path / "csv"))) == rows(g.edges)


def test_sql_surface(spark):
    g = graph(spark, TOY_LABELS, TOY_PAIRS).store()
    register(spark)
    register_graph(spark, "toy", g)
    n = spark.sql("SELECT count(DISTINCT n) FROM subgraph_matches_toy('(a:A)-(b:B)-(e:E)-(a)')").first()[0]
    assert n == 2
    assert rows(spark.sql("SELECT image FROM expand_packed(array(1L, 2L), array(2L, 3L, 4L))")) == [(3,), (4,)]
    assert spark.sql("SELECT intersect_sorted(array(1L, 2L, 5L), array(2L, 5L, 7L)) AS x").first()[0] == [2, 5]


def test_stream_equals_batch(spark, tmp_path):
    rng = random.Random(3)
    pairs = sorted({tuple(sorted(rng.sample(range(8), 2))) for _ in range(18)})
    g = graph(spark, {v: "A" for v in range(8)}, pairs)
    arcs = g.edges.collect()
    rng.shuffle(arcs)
    for k in range(3):
        spark.createDataFrame(arcs[k::3] + arcs[:2], "src long, dst long, elabel string").coalesce(1).write.parquet(str(tmp_path / "in" / f"f={k}"))
    stream = spark.readStream.schema("src long, dst long, elabel string").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(str(tmp_path / "in"))
    q = shape("triangle")
    out = S.stream_match(stream, g.vertices, q, str(tmp_path / "out"), str(tmp_path / "ck"))
    out.awaitTermination()
    got = [tuple(r)[:3] for r in spark.read.parquet(str(tmp_path / "out" / "matches")).select("a", "b", "c").collect()]
    assert len(got) == len(set(got)) and sorted(got) == brute(q, {v: "A" for v in range(8)}, {(a.src, a.dst) for a in arcs})


def test_event_streams(spark, tmp_path):
    rows_ = [(i, f"2024-01-01 00:{(i * 7) % 60:02d}:00", i % 3, ["view", "click", "buy"][i % 5 % 3], '{"k": 1}') for i in range(60)]
    df = spark.createDataFrame(rows_, "event_id long, t string, user_id long, event_type string, props string").withColumn("ts", F.to_timestamp("t")).drop("t")
    df.write.parquet(str(tmp_path / "ev"))
    stream = spark.readStream.schema(df.schema).parquet(str(tmp_path / "ev"))
    for name, plan, mode in (("pairs", S.temporal_pairs(stream, "view", "click"), "append"), ("chains", S.chains(stream, ["view", "click"]), "update"), ("arcs", S.new_arcs(stream), "append"), ("wins", S.window_counts(stream), "complete")):
        plan.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).option("checkpointLocation", str(tmp_path / name)).start().awaitTermination()
    assert rows(spark.table("pairs")) == rows(S.temporal_pairs(df, "view", "click")) == rows(S.binned_pairs(df, "view", "click"))
    assert rows(spark.table("wins")) == rows(S.window_counts(df))
    assert rows(spark.table("arcs")) == rows(S.new_arcs(df))
    want = {}
    for e in sorted(df.collect(), key=lambda r: (r.ts, r.event_id)):
        at, n = want.get(e.user_id, (0, 0))
        if e.event_type == ["view", "click"][at]:
            at, n = (at + 1, n) if at == 0 else (0, n + 1)
        want[e.user_id] = (at, n)
    assert {r.user_id: r.n for r in spark.table("chains").collect()} == {u: n for u, (_, n) in want.items()}


def test_prepare_reports_counts(spark):
    plan, cand, index = prepare(graph(spark, TOY_LABELS, TOY_PAIRS), TOY_QUERY, MatchSpec(filters=("label",)))
    assert plan.counts == (1, 1, 2, 3, 2, 2, 2)
    assert index.table().where("qa = 0 AND qb = 1").count() == 1


def test_regions_and_experiments(spark):
    from bundlegraph import experiments as X
    from bundlegraph import metrics

    g = graph(spark, TOY_LABELS, TOY_PAIRS).store()
    assert rows(match(g, TOY_QUERY, MatchSpec(engine="region")).flat()) == TOY_MATCHES
    assert rows(match(g, TOY_QUERY, MatchSpec(engine="kernel", kernel_arcs=0)).flat()) == TOY_MATCHES
    runs = X.run_all(g, {"toy": TOY_QUERY}, {k: X.METHODS[k] for k in ("full", "b1_dynamic_failing_set", "b10_sql_join")}, cap_s=600, repeats=1, warm_up=0).cache()
    assert {r.n for r in runs.collect()} == {8} and not any(r.timed_out for r in runs.collect())
    assert metrics.summary(runs).count() == 3 and metrics.against_second_best(runs, "full").count() == 1
    assert {r.n for r in X.limit_sweep(g, TOY_QUERY, (3, 100), {"full": MatchSpec(batches=2)}).collect()} == {3, 8}


@pytest.mark.parametrize("vectorised", [False, True])
def test_every_pair_of_lists_counts(spark, vectorised):
    from bundlegraph.queries import list_intersections

    rng = random.Random(9)
    lists = {v: sorted(rng.sample(range(30), rng.randint(1, 6))) for v in rng.sample(range(1000), 25)} | {2000: [0, 1, 2, 50], 2001: [0, 1, 2, 50]}
    df = spark.createDataFrame(list(lists.items()), "va long, nbrs array<long>")
    want = Counter(len(set(a) & set(b)) for a, b in itertools.combinations(lists.values(), 2))
    assert dict(rows(list_intersections(df, vectorised))) == want and want[0] and want[4]
    assert rows(list_intersections(df.limit(0), vectorised)) == rows(list_intersections(df.limit(1), vectorised)) == []


@pytest.mark.parametrize("seed", range(2))
def test_open_and_held_bundles_agree(spark, seed):
    """Random colourings, lists cut into parts, shared extensions, filters by statistics: all as brute force."""
    rng = random.Random(100 + seed)
    label = {v: rng.choice("AB") for v in range(10)}
    pairs = [(a, b) for a in range(10) for b in range(a) if rng.random() < 0.5]
    arcs = {x for a, b in pairs for x in ((a, b), (b, a))}
    g = graph(spark, label, pairs).store()
    q = shape(["tailed_triangle", "cycle4"][seed], {"a": "A"} if seed else {})
    want = brute(q, label, arcs)
    order = tuple(rng.sample(range(q.n), q.n))
    specs = [MatchSpec(order=order, colouring=tuple(rng.random() < 0.6 for _ in range(q.n)), lazy=k != 0, share="always" if k == 1 else "estimate", bundle_most=2 if k == 2 else 65_536, filters_skipped_at=0.0 if k == 3 else 0.8, injectivity="singleton" if k == 2 else "eager", broadcast_arcs=0 if k == 1 else 200_000) for k in range(4)]
    for spec in specs:
        r = match(g, q, spec)
        assert rows(r.flat()) == want, spec
        assert r.count().first()[0] == len(want), spec
        if spec.lazy == (seed == 1) or spec.share == "always":
            continue
        by = Counter((m[0], m[1]) for m in want)
        assert {(a, b): n for a, b, n in rows(r.count_by(q.names[0], q.names[1]))} == by, spec
        assert rows(r.select(q.names[1], distinct=True)) == sorted({(m[1],) for m in want}), spec


def test_typed_graphs_skip_idle_filters(spark):
    v = spark.createDataFrame([(i, "P") for i in range(6)] + [(10 + i, "O") for i in range(8)], "id long, label string")
    arcs = [(10 + o, p, "HAS") for o in range(8) for p in range(6) if (o * 7 + p * 3) % 4 < 2]
    e = spark.createDataFrame(arcs, "src long, dst long, elabel string")
    typed, plain = PropertyGraph(v, e, True, types={"HAS": ("O", "P")}), PropertyGraph(v, e, True)
    q = parse("(o:O)-[:HAS]->(p:P)<-[:HAS]-(x:O), (o)-[:HAS]->(z:P)", directed=True)
    r, s = match(typed, q), match(plain, q)
    assert r.index.marks is None and s.index.marks is not None
    assert rows(r.flat()) == rows(s.flat()) and r.count().first()[0] == s.count().first()[0] > 0
    twins = parse("(o:O)-[:HAS]->(p:P), (o)-[:HAS]->(x:P), (o)-[:HAS]->(z:P)", directed=True)
    a = match(typed, twins, MatchSpec(order=(0, 1, 2, 3), colouring=(False, True, True, True)))
    assert a.frontiers[-1].open == {1, 2, 3}
    assert a.count().first()[0] == a.flat().count() == match(plain, twins).flat().count()
    assert FEW > 1


def test_edge_predicates_and_returned_columns(spark):
    v = spark.createDataFrame([(i, "N") for i in range(5)], "id long, label string")
    e = spark.createDataFrame([(0, 1, "x", 5), (0, 1, "x", 1), (1, 2, "x", 3), (1, 3, "x", 9), (2, 4, "y", 9)], "src long, dst long, elabel string, w int")
    g = PropertyGraph(v, e, True)
    assert rows(match_sql(g, "(a)-[:x {w > 2}]->(b)-[{w > 5}]->(c)")) == [(0, 1, 3), (1, 2, 4)]
    assert rows(match_sql(g, "(a)-[:x]->(b)-[:x]->(c)")) == [(0, 1, 2), (0, 1, 3)]
    assert rows(match_sql(g, "(a)-[:x]->(b)-[:x]->(c) RETURN a, COUNT")) == [(0, 2)]
    assert rows(match_sql(g, "(a)-[:x]->(b)-[:x]->(c) RETURN DISTINCT a, b")) == [(0, 1)]
    assert rows(match_sql(g, "(a)-[:x]->(b)-[:x]->(c) RETURN COUNT")) == [(2,)]
    assert rows(match_sql(g, "(a)-[:x]->(b)-[:x]->(c) RETURN b")) == [(1,), (1,)]
    with pytest.raises(ValueError):
        match_sql(g, "(a)-[:x]->(b) RETURN z")
    q = parse("(a)-[:x {w > 2}]->(b)", directed=True)
    assert q.edge_where == ("w > 2",) and QueryGraph.from_json(q.to_json()) == q and q.restrict([0, 1]) == q
    assert rows(baselines.sql_join(g, q)) == [(0, 1), (1, 2), (1, 3)]


def test_a_cap_cancels_the_run(spark):
    slow = spark.range(4, numPartitions=4).select(F.udf(lambda i: __import__("time").sleep(60) or i, "long")("id").alias("x"))
    assert within(spark, 1.0, lambda: slow.agg(F.sum("x")).first()) == (None, True)
    assert within(spark, 60.0, lambda: 5) == (5, False) and within(spark, None, lambda: 6) == (6, False)
    with pytest.raises(ZeroDivisionError):
        within(spark, 60.0, lambda: 1 // 0)


def test_methods_must_agree(spark):
    from bundlegraph import experiments as X

    g = graph(spark, TOY_LABELS, TOY_PAIRS).store()
    with pytest.raises(AssertionError, match="disagree"):
        X.run_all(g, {"toy": TOY_QUERY}, {"a": X.METHODS["full"], "b": lambda g, q: (0.0, spark.range(1).selectExpr("7L AS n"))}, repeats=1, warm_up=0)


def test_saved_index_and_written_matches(spark, tmp_path):
    g = graph(spark, TOY_LABELS, TOY_PAIRS).store()
    r = match(g, TOY_QUERY)
    r.index.save("toy_index", 4)
    for i, j in r.index.links():
        assert rows(r.index.load("toy_index").pairs(i, j)) == rows(r.index.pairs(i, j))
    plan = r.index.load("toy_index").pairs(*r.index.links()[0]).groupBy("va").count()._jdf.queryExecution().toString()
    assert "Exchange hashpartitioning" not in plan
    for i, j in r.index.links():
        spark.sql(f"DROP TABLE toy_index_{i}_{j}"), spark.sql(f"DROP TABLE toy_index_{j}_{i}")
    r.write(str(tmp_path / "m"), packed=False)
    assert sorted(tuple(x)[:7] for x in spark.read.parquet(str(tmp_path / "m")).select(*TOY_QUERY.names).collect()) == TOY_MATCHES
    r.write(str(tmp_path / "p"))
    assert spark.read.parquet(str(tmp_path / "p")).count() == r.packed.count()


def test_dynamic_baselines_without_broadcast(spark):
    g = graph(spark, TOY_LABELS, TOY_PAIRS).store()
    assert rows(baselines.dynamic_failing_set(g, TOY_QUERY, baselines.PLAIN.but(kernel_arcs=0))) == TOY_MATCHES
    assert sorted(baselines.dynamic_batch_order(g, TOY_QUERY)) == list(range(7))


def test_scratch_tables_go_after_some_queries(spark):
    path = scratch.written(spark.range(3), "gone")._jdf.inputFiles()[0].rsplit("/", 1)[0]
    assert scratch.path_exists(spark, path)
    for _ in range(scratch.SCOPES):
        scratch.new_scope(spark)
    assert not scratch.path_exists(spark, path)


def test_triples_and_late_chains_on_streams(spark, tmp_path):
    rng = random.Random(4)
    kinds = ["view", "click", "buy"]
    all_rows = [(i, f"2024-01-01 {i // 60:02d}:{i % 60:02d}:00", i % 2, rng.choice(kinds)) for i in range(120)]
    shuffled = all_rows[:]
    for k in range(0, 120, 20):  # out of order within twenty minutes
        part = shuffled[k : k + 20]
        rng.shuffle(part)
        shuffled[k : k + 20] = part
    far = [(1000 + u, "2024-01-09 00:00:00", u, "end") for u in (0, 1, 7)] + [(2000, "2024-01-20 00:00:00", 7, "end")]
    schema = "event_id long, t string, user_id long, event_type string"
    batches = [shuffled[k : k + 10] for k in range(0, 120, 10)] + [far[:3], far[3:], [(3000, "2024-01-20 00:00:01", 7, "end")]]
    for k, part in enumerate(batches):
        spark.createDataFrame(part, schema).withColumn("ts", F.to_timestamp("t")).drop("t").coalesce(1).write.parquet(str(tmp_path / "ev" / f"b={k:02d}"))
    table = spark.createDataFrame(all_rows, schema).withColumn("ts", F.to_timestamp("t")).drop("t")
    read = lambda: spark.readStream.schema("event_id long, user_id long, event_type string, ts timestamp").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").option("latestFirst", "false").parquet(str(tmp_path / "ev"))
    for name, plan, mode in (("triples", S.temporal_triples(read(), tuple(kinds), "10 minutes"), "append"), ("late_chains", S.chains(read(), kinds[:2], late="30 minutes"), "update")):
        q = plan.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).option("checkpointLocation", str(tmp_path / name)).start()
        q.awaitTermination()
        assert S.late_rows(q) == 0
    assert rows(spark.table("triples")) == rows(S.temporal_triples(table, tuple(kinds), "10 minutes"))
    want = {}
    for e in sorted(table.collect(), key=lambda r: (r.ts, r.event_id)):
        at, n = want.get(e.user_id, (0, 0))
        at = at + 1 if e.event_type == kinds[at] else at
        want[e.user_id] = (0, n + 1) if at == 2 else (at, n)
    got = {}
    for r in spark.table("late_chains").collect():
        got[r.user_id] = max(got.get(r.user_id, 0), r.n)
    assert {u: n for u, n in got.items() if u in want} == {u: n for u, (_, n) in want.items()}

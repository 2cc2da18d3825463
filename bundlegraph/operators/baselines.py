"""Behavioural stand-ins for the compared methods: their printed traits, in this engine.

None claims the speed of an original; they are here so that what each trait costs or saves can be
counted on equal terms. All return flat matches but where said.
"""

from __future__ import annotations

import time
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.scratch import written
from ..model import MatchPlan, MatchSpec, PropertyGraph, QueryGraph
from .batched import batched
from .filters import arcs_of, filter_masks
from .kernel import DynamicSearch, search_tasks, driver_lists, search_regions
from .match import MatchResult, match, prepare

PLAIN = MatchSpec(reuse=None, prune_dominated=False, prune_failing=False)


def _dynamic(g: PropertyGraph, q: QueryGraph, spec: MatchSpec, failing: bool, classes: bool, clock: dict | None = None) -> DataFrame:
    """The next vertex is chosen for each partial match, which no set-at-a-time plan can do: a task
    searches its roots over a broadcast index of checked size, or beyond that each root over its region.
    """
    g, began = g.store(), time.time()
    spec = spec.but(colouring="all_pinned", prune_dominated=False)
    plan, cand, index = prepare(g, q, spec)
    lists = driver_lists(index, spec.kernel_arcs)
    place = [plan.order.index(u) for u in range(q.n)]
    schema = T.StructType([T.StructField(n, T.LongType()) for n in q.names])
    if clock is not None:
        clock["pre_ms"] = (time.time() - began) * 1e3
    if lists is None:

        def one(root: int, lists) -> list[list]:
            s = DynamicSearch(plan, lists, _ends(plan, lists, {0: {root}}), spec, failing, classes)
            return [[m[p] for p in place] for m in s.run({0: root}, {0: 1})[0]]

        return search_regions(index, plan, cand, schema, one)
    ends = _ends(plan, lists, {})
    for i in range(q.n):  # places without a link: their candidates are no larger than the index may be
        if not any(i in link for link in index.links()):
            ends[i] = frozenset(r.id for r in cand[plan.order[i]].limit(spec.kernel_arcs + 1).collect())
            if len(ends[i]) > spec.kernel_arcs:
                raise ValueError("a query vertex without a link has too many candidates to be broadcast")
    shared = index.spark.sparkContext.broadcast((plan, lists, ends, spec))

    def run(batches):
        import pyarrow as pa

        plan, lists, ends, spec = shared.value
        s = DynamicSearch(plan, lists, ends, spec, failing, classes)
        for b in batches:
            for v in b.column(0).to_pylist():
                got = s.run({0: v}, {0: 1})[0]
                yield pa.RecordBatch.from_arrays([pa.array([m[p] for m in got], pa.int64()) for p in place], list(q.names))

    return cand[plan.order[0]].select("id").repartition(search_tasks(index.spark), "id").mapInArrow(run, schema)


def _ends(plan: MatchPlan, lists, given: dict[int, set[int]]) -> list[frozenset[int]]:
    """Candidates of each place as far as the index links them."""
    return [frozenset(given.get(i) or {v for (a, _), d in lists.items() if a == i for v in d}) for i in range(plan.query.n)]


def dynamic_failing_set(g: PropertyGraph, q: QueryGraph, spec: MatchSpec = PLAIN, clock: dict | None = None) -> DataFrame:
    """Dynamic order and failing sets."""
    return _dynamic(g, q, spec, failing=True, classes=False, clock=clock)


def static_leaf_grouping(g: PropertyGraph, q: QueryGraph, spec: MatchSpec = PLAIN) -> MatchResult:
    """Static order; only vertices without later links are kept as sets."""
    return match(g, q, spec.but(colouring="tail_only", order="dense_first"))


def dynamic_equivalence(g: PropertyGraph, q: QueryGraph, spec: MatchSpec = PLAIN, clock: dict | None = None) -> DataFrame:
    """Dynamic order; candidates with equal index rows are searched once."""
    return _dynamic(g, q, spec, failing=True, classes=True, clock=clock)


def guarded(g: PropertyGraph, q: QueryGraph, spec: MatchSpec = PLAIN, clock: dict | None = None) -> DataFrame:
    """Static order, one image a vertex; keys that led nowhere are kept out of later batches."""
    found, facts = batched(g, q, spec.but(colouring="all_pinned", order="guard_first", batches=4), nogoods=True)
    if clock is not None:
        clock["pre_ms"] = facts["pre_ms"]
    return found


def neighbour_classes(g: PropertyGraph, q: QueryGraph, spec: MatchSpec = PLAIN, clock: dict | None = None) -> DataFrame:
    """Dynamic order; candidates with the same neighbours form classes, without failing sets."""
    return _dynamic(g, q, spec, failing=False, classes=True, clock=clock)


def batch_homomorphism(g: PropertyGraph, q: QueryGraph, spec: MatchSpec = PLAIN) -> MatchResult:
    """Everything carried as sets in an order chosen on the way; injectivity is checked only when
    matches are written out."""
    g = g.store()
    return match(g, q, spec.but(colouring="all_bundled", injectivity="late", order=dynamic_batch_order(g, q, spec)))


def dynamic_batch_order(g: PropertyGraph, q: QueryGraph, spec: MatchSpec = PLAIN) -> tuple[int, ...]:
    """An order for whole batches: next comes the query vertex of which the placed vertices' images
    that are still alive reach the fewest candidates, counted anew at each step."""
    masks = filter_masks(g, q, spec)
    counts = masks.counts()[0]
    order: list[int] = []
    alive: dict[int, DataFrame] = {}
    while len(order) < q.n:
        ready = sorted({j for i in order for j in q.neighbours(i)} - set(order))
        if not ready:
            u = min(set(range(q.n)) - set(order), key=lambda v: (counts[v], v))
            alive[u] = masks.ids(u)
        else:
            reach = {}
            for u in ready:
                left = masks.ids(u)
                for (a, b), arcs in q.links().items():
                    if u in (a, b) and (a in alive or b in alive):
                        w = a if b == u else b
                        for x, y, e in arcs:
                            mine, other = ("src", "dst") if x == u else ("dst", "src")
                            near = arcs_of(g, e).join(alive[w].select(F.col("id").alias(other)).hint("merge"), other, "left_semi")
                            left = left.join(near.select(F.col(mine).alias("id")).hint("merge"), "id", "left_semi")
                reach[u] = left
            sizes = {r.u: r.n for r in reduce(DataFrame.unionByName, [d.select(F.lit(u).alias("u")) for u, d in reach.items()]).groupBy("u").agg(F.count("*").alias("n")).collect()}
            u = min(ready, key=lambda v: (sizes.get(v, 0), v))
            alive[u] = written(reach[u], "alive")
        order.append(u)
    return tuple(order)


def backtracking(g: PropertyGraph, q: QueryGraph, spec: MatchSpec = PLAIN) -> MatchResult:
    """Plain depth-first search, one image a vertex."""
    return match(g, q, spec.but(colouring="all_pinned", engine="kernel"))


def level_by_level(g: PropertyGraph, q: QueryGraph, share: bool = True, spec: MatchSpec = PLAIN) -> MatchResult:
    """Breadth first, with or without grouping partial matches of equal extensions."""
    return match(g, q, spec.but(colouring="all_pinned", reuse="bn" if share else None, share="always"))


def vertex_cover(g: PropertyGraph, q: QueryGraph, spec: MatchSpec = PLAIN) -> MatchResult:
    """Sets only on an independent set, so sets never meet."""
    return match(g, q, spec.but(colouring="vertex_cover"))


def sql_join(g: PropertyGraph, q: QueryGraph, semantics: str = "iso") -> DataFrame:
    """The query as one multiway join; Catalyst picks the joins."""
    df: DataFrame | None = None
    done: list[int] = []
    while len(done) < q.n:
        left = [i for i in range(q.n) if i not in done]
        i = next((i for i in left if not done or q.neighbours(i) & set(done)), left[0])
        side = g.vertices if q.labels[i] is None else g.vertices.where(F.col("label") == q.labels[i])
        side = side.where(q.where[i]) if q.where and q.where[i] else side
        side = side.select(F.col("id").alias(q.names[i])).distinct()
        for k, (a, b, e) in enumerate(q.edges):
            if i in (a, b) and {a, b} <= {*done, i}:
                arc = g.edges if e is None else g.edges.where(F.col("elabel") == e)
                arc = arc.where(q.edge_test(k)) if q.edge_test(k) else arc
                arc = arc.select(F.col("src").alias(q.names[a]), F.col("dst").alias(f"__{q.names[a]}" if a == b else q.names[b])).distinct()
                if a != b and semantics != "hom":  # loops match nothing, and arcs that are stored once are not made distinct again
                    arc = arcs_of(g, e, q.edge_test(k)).select(F.col("src").alias(q.names[a]), F.col("dst").alias(q.names[b]))
                if a == b:
                    side = side.join(arc.where(F.col(q.names[a]) == F.col(f"__{q.names[a]}")).select(q.names[a]), q.names[a], "left_semi")
                else:
                    df = arc if df is None else df.join(arc, [n for n in arc.columns if n in df.columns])
        df = side if df is None else df.join(side, q.names[i]) if q.names[i] in df.columns else df.crossJoin(side)
        done.append(i)
    if semantics != "hom":
        for i in range(q.n):
            for j in range(i):
                if q.may_clash(i, j):
                    df = df.where(F.col(q.names[i]) != F.col(q.names[j]))
    return df.select(*q.names)

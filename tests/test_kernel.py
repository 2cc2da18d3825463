"""The search core against brute force on random small graphs, without Spark."""

import itertools
import random

import pytest

from bundlegraph.model import MatchSpec, QueryGraph
from bundlegraph.operators.kernel import DynamicSearch, Search
from bundlegraph.plans.analysis import make_plan


def brute(q, label, arcs, iso=True):
    out, ids = set(), sorted(label)
    opts = [[v for v in ids if q.labels[u] in (None, label[v])] for u in range(q.n)]
    for m in itertools.product(*opts):
        if (not iso or len(set(m)) == q.n) and all((m[a], m[b]) in arcs for a, b, _ in q.edges):
            out.add(m)
    return out


def setup(q, label, arcs, spec, filtered):
    cand = [frozenset(v for v in label if q.labels[u] in (None, label[v])) for u in range(q.n)]
    if filtered:
        for _ in range(2):
            cand = [frozenset(v for v in c if all(any((v, x) in arcs for x in cand[w]) for w in q.neighbours(u))) for u, c in enumerate(cand)]
    inside = lambda plan_order: lambda i, j: cand[plan_order[j]] <= cand[plan_order[i]]
    first = make_plan(q, [len(c) for c in cand], spec.but(prune_dominated=False))
    plan = make_plan(q, [len(c) for c in cand], spec, inside(first.order))
    lists = {}
    for i in range(q.n):
        for j in range(q.n):
            u, w = plan.order[i], plan.order[j]
            if w in q.neighbours(u):
                lists[i, j] = {v: frozenset(x for x in cand[w] if (v, x) in arcs) for v in cand[u]}
    return plan, lists, [cand[u] for u in plan.order]


def expanded(plan, images, iso):
    out = []
    for image in images:
        for m in itertools.product(*[sorted(x) if b else (x,) for x, b in zip(image, plan.bundled)]):
            if not iso or all(m[i] != m[j] or not plan.clash(i, j) for i in range(len(m)) for j in range(i)):
                out.append(tuple(m[plan.order.index(u)] for u in range(len(m))))
    return out


def random_case(rng):
    n = rng.randint(6, 9)
    label = {v: rng.choice("ABC"[: rng.randint(1, 3)]) for v in range(n)}
    arcs = set()
    p = rng.uniform(0.2, 0.5)
    for a in range(n):
        for b in range(a):
            if rng.random() < p:
                arcs |= {(a, b), (b, a)}
    k = rng.randint(3, 5)
    edges = {(rng.randrange(i), i) for i in range(1, k)}
    for _ in range(rng.randint(0, 3)):
        a, b = sorted(rng.sample(range(k), 2))
        edges.add((a, b))
    q = QueryGraph(tuple(f"u{i}" for i in range(k)), tuple(rng.choice(sorted(set(label.values()))) for _ in range(k)), tuple((a, b, None) for a, b in sorted(edges)))
    return q, label, arcs


@pytest.mark.parametrize("seed", range(12))
def test_search_equals_brute_force(seed):
    rng = random.Random(seed)
    for _ in range(60):
        q, label, arcs = random_case(rng)
        for iso in (True, False):
            want = sorted(brute(q, label, arcs, iso))
            for colouring in ("risk", "risk_smoothed", "all_pinned", "all_bundled", "tail_only", "vertex_cover", tuple(rng.random() < 0.5 for _ in range(q.n))):
                spec = MatchSpec(semantics="iso" if iso else "hom", colouring=colouring, reuse=rng.choice(["bn", None]), prune_dominated=rng.random() < 0.7, prune_failing=rng.random() < 0.7)
                plan, lists, cand = setup(q, label, arcs, spec, rng.random() < 0.5)
                images = []
                s = Search(plan, lists, cand, spec)
                s.roots([frozenset(cand[0])] if plan.bundled[0] and cand[0] else [] if plan.bundled[0] else sorted(cand[0]), lambda im: images.append(list(im)))
                assert sorted(expanded(plan, images, iso)) == want, (q, label, arcs, spec)
            for failing, classes in ((True, False), (False, True), (True, True)):
                spec = MatchSpec(semantics="iso" if iso else "hom", colouring="all_pinned")
                plan, lists, cand = setup(q, label, arcs, spec, False)
                d = DynamicSearch(plan, lists, cand, spec, failing, classes)
                got = [m for v in sorted(cand[0]) for m in d.run({0: v}, {0: 1})[0]]
                assert sorted(tuple(m[plan.order.index(u)] for u in range(q.n)) for m in got) == want


def test_filtered_candidates_do_not_break_the_size_test():
    q = QueryGraph(("u0", "u1", "u2", "u3", "u4"), ("A", "B", "B", "B", "C"), ((0, 1, None), (0, 2, None), (0, 3, None), (1, 4, None)))
    label = {0: "A", 1: "B", 2: "B", 3: "B", 4: "C"}
    arcs = {x for a, b in ((0, 1), (0, 2), (0, 3), (1, 4)) for x in ((a, b), (b, a))}
    for filtered in (True, False):
        plan, lists, cand = setup(q, label, arcs, MatchSpec(), filtered)
        images = []
        Search(plan, lists, cand, MatchSpec()).roots(sorted(cand[0]) if not plan.bundled[0] else [cand[0]], lambda im: images.append(list(im)))
        assert len(expanded(plan, images, True)) == 2


def test_failing_sets_are_closed():
    q = QueryGraph(("u0", "u1", "u2", "u3", "u4"), ("A", "J", "W", "K", "X"), ((0, 1, None), (0, 2, None), (1, 3, None), (2, 3, None), (1, 4, None)))
    r, j1, j2, w1, w2, k1, k2, x = range(8)
    label = dict(zip(range(8), "AJJWWKKX"))
    arcs = {y for a, b in ((r, j1), (r, j2), (r, w1), (r, w2), (k1, w1), (k1, j1), (k2, w2), (k2, j2), (x, j2)) for y in ((a, b), (b, a))}
    spec = MatchSpec(order=(0, 1, 2, 3, 4), colouring=(False, True, False, False, False))
    plan, lists, cand = setup(q, label, arcs, spec, False)
    images = []
    Search(plan, lists, cand, spec).roots(sorted(cand[0]), lambda im: images.append(list(im)))
    assert expanded(plan, images, True) == [(r, j2, w2, k2, x)]

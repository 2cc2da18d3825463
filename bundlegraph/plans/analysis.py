"""What an extension depends on, and which later vertices an extension set must also host."""

from __future__ import annotations

from ..model import MatchPlan, MatchSpec, QueryGraph
from .colouring import COLOURINGS
from .ordering import ORDERS


def back_sets(q: QueryGraph, order: tuple[int, ...]) -> list[tuple[int, ...]]:
    at = {u: i for i, u in enumerate(order)}
    return [tuple(sorted(at[w] for w in q.neighbours(u) if at[w] < i)) for i, u in enumerate(order)]


def closed(start: set[int], upto: int, back: list[tuple[int, ...]], bundled: tuple[bool, ...]) -> frozenset[int]:
    """Least superset closed under back-neighbours and, for bundled members, under all links below `upto`."""
    out, todo = set(), list(start)
    while todo:
        w = todo.pop()
        if w in out:
            continue
        out.add(w)
        todo += back[w]
        if bundled[w]:
            todo += [x for x in range(upto) if w in back[x]]
    return frozenset(out)


def dependency_sets(back: list[tuple[int, ...]], bundled: tuple[bool, ...]) -> list[frozenset[int]]:
    """Places whose images fix the extension set: all that the back-neighbours' images come from."""
    out = []
    for i in range(len(back)):
        direct = set(back[i]) | {x for w in back[i] if bundled[w] for x in range(i) if w in back[x]}
        todo, seen = list(direct), set()
        while todo:
            w = todo.pop()
            if w not in seen:
                seen.add(w)
                todo += back[w]
        out.append(frozenset(seen))
    return out


def dominated_sets(q: QueryGraph, order: tuple[int, ...], back: list[tuple[int, ...]], inside=None) -> list[frozenset[int]]:
    """Later places of the same label that link at least where place i does, by arcs of the same kind.

    inside(i, j) tells whether the candidates of j lie among those of i; without that proof the
    size test would not be sound on filtered candidates, so such a j does not count.
    """
    links = q.links()

    def kinds(i: int, w: int) -> set:
        u, x = order[i], order[w]
        return {((a == u), e) for a, b, e in links[min(u, x), max(u, x)]}

    out = []
    for i in range(q.n):
        found = set()
        for j in range(i + 1, q.n):
            same = q.labels[order[i]] == q.labels[order[j]] and back[i] and set(back[i]) <= set(back[j])
            if same and all(kinds(i, w) <= kinds(j, w) for w in back[i]) and (inside is None or inside(i, j)):
                found.add(j)
        out.append(frozenset(found))
    return out


def make_plan(q: QueryGraph, counts: list[int], spec: MatchSpec, inside=None) -> MatchPlan:
    order = tuple(spec.order) if not isinstance(spec.order, str) else ORDERS[spec.order](q, counts)
    bundled = tuple(spec.colouring) if not isinstance(spec.colouring, str) else COLOURINGS[spec.colouring](q, order, counts)
    tied = {order.index(x) for a, _, b in q.cross for x in (a, b)}  # compared vertices need one image each
    bundled = tuple(b and i not in tied for i, b in enumerate(bundled))
    back = back_sets(q, order)
    depends = dependency_sets(back, bundled)
    anchor = tuple(max(d) if d else -1 for d in depends)
    reusable = tuple(i > 0 and anchor[i] < i - 1 for i in range(q.n))
    dom = dominated_sets(q, order, back, inside) if spec.prune_dominated and spec.semantics != "hom" else [frozenset()] * q.n
    return MatchPlan(q, order, bundled, tuple(counts), tuple(back), tuple(depends), anchor, reusable, tuple(dom), tuple(1 + len(d) for d in dom))

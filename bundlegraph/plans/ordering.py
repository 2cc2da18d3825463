"""Matching orders: greedy by candidate ratio, and four static orders to compare with."""

from __future__ import annotations

from collections.abc import Callable

from ..model import QueryGraph


def _grow(q: QueryGraph, first: Callable[[int], tuple], rank: Callable[[int, set[int]], tuple]) -> tuple[int, ...]:
    """Start at the vertex of least `first`; go on with the neighbour of the prefix of least `rank`.

    Ties go to the smaller vertex. A disconnected query starts anew in each component.
    """
    order: list[int] = []
    while len(order) < q.n:
        done = set(order)
        edge = {j for i in done for j in q.neighbours(i)} - done
        order.append(min(edge, key=lambda u: (*rank(u, done), u)) if edge else min(set(range(q.n)) - done, key=lambda u: (*first(u), u)))
    return tuple(order)


def by_candidate_ratio(q: QueryGraph, counts: list[int]) -> tuple[int, ...]:
    """Few candidates for each link: first over all links, then over links into the prefix."""
    return _grow(q, lambda u: (counts[u] / max(1, len(q.neighbours(u))),), lambda u, done: (counts[u] / len(q.neighbours(u) & done),))


def dense_first(q: QueryGraph, counts: list[int]) -> tuple[int, ...]:
    """Own stand-in: densest neighbourhood of the query first, then most links into the prefix."""

    def density(u: int) -> int:
        around = q.neighbours(u) | {u}
        return sum(1 for a, b in q.links() if a in around and b in around)

    return _grow(q, lambda u: (-density(u),), lambda u, done: (-len(q.neighbours(u) & done), -density(u)))


def guard_first(q: QueryGraph, counts: list[int]) -> tuple[int, ...]:
    """Own stand-in: small candidate sets of well-linked vertices first."""
    return _grow(q, lambda u: (counts[u], -len(q.neighbours(u))), lambda u, done: (counts[u], -len(q.neighbours(u))))


def structure_first(q: QueryGraph, counts: list[int]) -> tuple[int, ...]:
    """Own stand-in: the query's structure only; most links into the prefix, then into its border."""

    def ahead(u: int, done: set[int]) -> int:
        return len(q.neighbours(u) - done)

    return _grow(q, lambda u: (-len(q.neighbours(u)),), lambda u, done: (-len(q.neighbours(u) & done), -ahead(u, done)))


def smallest_candidates(q: QueryGraph, counts: list[int]) -> tuple[int, ...]:
    """Own stand-in: the smallest candidate set next to the prefix."""
    return _grow(q, lambda u: (counts[u],), lambda u, done: (counts[u],))


ORDERS = {"candidate_ratio": by_candidate_ratio, "dense_first": dense_first, "guard_first": guard_first, "structure_first": structure_first, "smallest_candidates": smallest_candidates}

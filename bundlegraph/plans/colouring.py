"""Which query vertices carry sets. True means bundled, by place in the order."""

from __future__ import annotations

from ..model import QueryGraph


def _back_forward(q: QueryGraph, order: tuple[int, ...]) -> list[tuple[set[int], set[int]]]:
    at = {u: i for i, u in enumerate(order)}
    near = [{at[w] for w in q.neighbours(u)} for u in order]
    return [({j for j in near[i] if j < i}, {j for j in near[i] if j > i}) for i in range(q.n)]


def by_risk(q: QueryGraph, order: tuple[int, ...], counts: list[int], smooth: int = 0) -> tuple[bool, ...]:
    """Bundle a vertex if carrying its set risks less repeated work than pinning it.

    Bundling risks later splits (candidates of forward neighbours), label conflicts (vertices of
    the same label) and splits of bundled back-neighbours; pinning risks one branch for each
    candidate over pinned back-neighbours. `smooth` is added to the count of bundled back-neighbours.
    """
    size = [counts[u] for u in order]
    out: list[bool] = []
    for i, (back, ahead) in enumerate(_back_forward(q, order)):
        same = sum(1 for w in order if q.labels[w] == q.labels[order[i]])
        bundled = sum(1 for j in back if out[j])
        bundle_risk = (1 + sum(size[j] for j in ahead)) * same * (bundled + smooth)
        out.append(bundle_risk < size[i] * (len(back) - bundled) and bool(back))
    return tuple(out)


def tail_only(q: QueryGraph, order: tuple[int, ...], counts: list[int]) -> tuple[bool, ...]:
    """Bundle what nothing later depends on."""
    return tuple(bool(back) and not ahead for back, ahead in _back_forward(q, order))


def vertex_cover(q: QueryGraph, order: tuple[int, ...], counts: list[int]) -> tuple[bool, ...]:
    """Bundle an independent set (the rest covers all links), so two bundles are never linked."""
    near = _back_forward(q, order)
    out = [False] * q.n
    for i in sorted(range(q.n), key=lambda k: (len(near[k][0]) + len(near[k][1]), -k)):
        out[i] = i > 0 and not any(out[j] for j in near[i][0] | near[i][1])
    return tuple(out)


COLOURINGS = {
    "risk": by_risk,
    "risk_smoothed": lambda q, o, c: by_risk(q, o, c, smooth=1),
    "all_pinned": lambda q, o, c: (False,) * q.n,
    "all_bundled": lambda q, o, c: (True,) * q.n,
    "tail_only": tail_only,
    "vertex_cover": vertex_cover,
}

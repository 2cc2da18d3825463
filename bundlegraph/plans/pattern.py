"""A small pattern language: (a:part {p_size > 10})-[:CONTAINS {quantity > 5}]->(b:orders), (b)-(c); a < c"""

from __future__ import annotations

import re

from ..model import QueryGraph

_NODE = re.compile(r"\s*\(\s*(\w+)\s*(?::\s*([^\s){]+))?\s*(?:\{(.*?)\})?\s*\)")
_EDGE = re.compile(r"\s*(<)?-(?:\[\s*(?::\s*([^\]\s{]+))?\s*(?:\{(.*?)\})?\s*\]-)?(>)?")


def parse(text: str, directed: bool | None = None) -> QueryGraph:
    """Chains of nodes and edges, parted by commas; after a semicolon comparisons of two nodes.

    Arrows make the query directed. A node's label and predicate need to stand only once; an edge may
    have a label, a predicate on arc columns, or both.
    """
    body, _, tests = text.partition(";")
    labels: dict[str, str | None] = {}
    where: dict[str, str] = {}
    edges, arrows, at = [], False, 0

    def node() -> str:
        nonlocal at
        m = _NODE.match(body, at)
        if not m:
            raise ValueError(f"a node is expected at: {body[at:at + 30]!r}")
        at = m.end()
        name, label, pred = m.groups()
        if label and labels.get(name) not in (None, label):
            raise ValueError(f"node {name} has two labels")
        labels[name] = label or labels.get(name)
        if pred:
            where[name] = pred.strip()
        return name

    while True:
        left = node()
        while at < len(body) and body[at:].lstrip()[:1] in ("-", "<"):
            m = _EDGE.match(body, at)
            if not m or (m[1] and m[4]):
                raise ValueError(f"an edge is expected at: {body[at:at + 30]!r}")
            at = m.end()
            right = node()
            arrows |= bool(m[1] or m[4])
            test = m[3].strip() if m[3] else None
            edges.append((right, left, m[2], test) if m[1] else (left, right, m[2], test))
            left = right
        rest = body[at:].lstrip()
        if not rest:
            break
        if rest[0] != ",":
            raise ValueError(f"a comma is expected at: {rest[:30]!r}")
        at = len(body) - len(rest) + 1
    cross = []
    for t in filter(None, (x.strip() for x in tests.split(","))):
        m = re.fullmatch(r"(\w+)\s*(<=|>=|<>|<|>)\s*(\w+)", t)
        if not m:
            raise ValueError(f"not a comparison of two nodes: {t!r}")
        cross.append((m[1], m[2], m[3]))
    return QueryGraph.of(labels, edges, arrows if directed is None else directed, where, cross)

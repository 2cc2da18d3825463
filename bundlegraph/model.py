"""Graphs as tables, queries as small driver-side objects, and the plan that joins both."""

from __future__ import annotations

import json
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .functions.scratch import scratch_path


@dataclass(frozen=True)
class QueryGraph:
    """A small pattern. `edges` holds (from, to, edge label or None) by vertex index.

    In an undirected graph both arcs of an edge are stored, so one query arc for each edge is enough.
    `where` holds one SQL predicate on vertex columns (or None) for each vertex, `edge_where` one on
    arc columns for each edge; `cross` holds (i, operator, j) comparisons of two vertices' ids.
    """

    names: tuple[str, ...]
    labels: tuple[str | None, ...]
    edges: tuple[tuple[int, int, str | None], ...]
    directed: bool = False
    where: tuple[str | None, ...] = ()
    cross: tuple[tuple[int, str, int], ...] = ()
    edge_where: tuple[str | None, ...] = ()

    @staticmethod
    def of(
        labels: dict[str, str | None], edges: list[tuple], directed: bool = False, where: dict[str, str] | None = None,
        cross: list[tuple[str, str, str]] | None = None,
    ) -> "QueryGraph":
        """edges: (from, to), (from, to, label) or (from, to, label, predicate), by name."""
        names = tuple(labels)
        at = {n: i for i, n in enumerate(names)}
        arcs = tuple((at[e[0]], at[e[1]], e[2] if len(e) > 2 else None) for e in edges)
        tests = tuple(e[3] if len(e) > 3 else None for e in edges)
        compared = tuple((at[a], op, at[b]) for a, op, b in cross or ())
        return QueryGraph(
            names, tuple(labels.values()), arcs, directed, tuple((where or {}).get(n) for n in names), compared,
            tests if any(tests) else (),
        )

    @property
    def n(self) -> int:
        return len(self.names)

    def edge_test(self, k: int) -> str | None:
        return self.edge_where[k] if self.edge_where else None

    def links(self) -> dict[tuple[int, int], list[tuple[int, int, str | None]]]:
        """Arcs by unordered pair of different vertices."""
        return {pair: [self.edges[k] for k in ks] for pair, ks in self.link_arcs().items()}

    def link_arcs(self) -> dict[tuple[int, int], list[int]]:
        """Numbers of the arcs by unordered pair of different vertices."""
        out: dict[tuple[int, int], list] = {}
        for k, (a, b, _) in enumerate(self.edges):
            if a != b:
                out.setdefault((min(a, b), max(a, b)), []).append(k)
        return out

    def neighbours(self, i: int) -> set[int]:
        return {b if a == i else a for a, b in self.links() if i in (a, b)}

    def loops(self, i: int) -> list[str | None]:
        return [e for a, b, e in self.edges if a == b == i]

    def may_clash(self, i: int, j: int) -> bool:
        """Can both have the same image?"""
        return self.labels[i] is None or self.labels[j] is None or self.labels[i] == self.labels[j]

    def components(self) -> list[list[int]]:
        left, out = set(range(self.n)), []
        while left:
            todo, part = [min(left)], set()
            while todo:
                i = todo.pop()
                if i not in part:
                    part.add(i)
                    todo += self.neighbours(i) - part
            out.append(sorted(part))
            left -= part
        return out

    def restrict(self, keep: list[int]) -> "QueryGraph":
        """The query induced on some of its vertices, in the given order."""
        at = {v: k for k, v in enumerate(keep)}
        inner = [k for k, (a, b, _) in enumerate(self.edges) if a in at and b in at]
        return QueryGraph(
            tuple(self.names[i] for i in keep), tuple(self.labels[i] for i in keep),
            tuple((at[self.edges[k][0]], at[self.edges[k][1]], self.edges[k][2]) for k in inner), self.directed,
            tuple(self.where[i] for i in keep) if self.where else (),
            tuple((at[a], o, at[b]) for a, o, b in self.cross if a in at and b in at),
            tuple(self.edge_where[k] for k in inner) if self.edge_where else (),
        )

    def to_json(self) -> str:
        return json.dumps({
            "names": self.names, "labels": self.labels, "edges": self.edges, "directed": self.directed,
            "where": self.where, "cross": self.cross, "edge_where": self.edge_where,
        })

    @staticmethod
    def from_json(text: str) -> "QueryGraph":
        d = json.loads(text)
        return QueryGraph(
            tuple(d["names"]), tuple(d["labels"]), tuple(map(tuple, d["edges"])), d["directed"], tuple(d["where"]),
            tuple(map(tuple, d["cross"])), tuple(d.get("edge_where", ())),
        )


@dataclass(frozen=True)
class GraphStats:
    """What a stored graph knows of itself: one small row for each vertex label and kind of arc.

    `ends[kind, side]` holds how many vertices have at least 1, 2, ... STEPS arcs of that kind on
    that side ("out" or "in"), `top[kind, side]` the most that one has. Loops do not count.
    """

    labels: dict[str | None, int]
    arcs: dict[str | None, int]
    ends: dict[tuple[str | None, str], tuple[int, ...]]
    top: dict[tuple[str | None, str], int]


STEPS = 8
#: Labels or kinds of arcs beyond this are not collected; the graph then has no statistics.
MOST_LABELS = 10_000


@dataclass
class PropertyGraph:
    """vertices(id, label, ...), edges(src, dst, elabel, ...). Undirected graphs store both arcs.

    `types` declares for each kind of arc the labels of its two ends, which all its arcs then have
    and which exist as vertices; it lets the label test be left out where the arc implies it.
    """

    vertices: DataFrame
    edges: DataFrame
    directed: bool = False
    stored: bool = False
    types: dict[str, tuple[str, str]] | None = None
    stats: GraphStats | None = None
    path: str | None = None

    @property
    def properties(self) -> list[str]:
        return [c for c in self.edges.columns if c not in ("src", "dst", "elabel")]

    def store(self, keep: bool = False) -> "PropertyGraph":
        """The same graph with its distinct arcs as a table and its statistics; builders may be
        costly to run twice. Declared kinds of arcs get a folder each. keep: for the whole session."""
        if self.stored:
            return self
        spark = self.edges.sparkSession
        path = scratch_path(spark, "arcs", keep)
        rows = self.edges.select("src", "dst", "elabel", *self.properties).distinct()
        out = rows.write.partitionBy("elabel") if self.types else rows.write
        out.parquet(path)
        kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema)
        arcs = spark.read.schema(kinds).parquet(path).select(*rows.columns)
        g = PropertyGraph(self.vertices, arcs, self.directed, True, self.types, path=path)
        g.stats = measure(g)
        return g


def measure(g: PropertyGraph) -> GraphStats | None:
    """Statistics of a stored graph, from one pass over its vertices and two over its arcs."""
    labels = g.vertices.where("id IS NOT NULL").groupBy("label").agg(F.count("*").alias("n"))
    labels = labels.select(F.lit("").alias("side"), F.col("label").alias("kind"), F.col("n").alias("arcs"), F.lit(0).cast("long").alias("top"), F.array(F.lit(0).cast("long")).alias("ends"))
    arcs = g.edges.where("src <> dst").select("src", "dst", "elabel")
    arcs = arcs.distinct() if g.properties else arcs
    parts = [labels]
    for side, end in (("out", "src"), ("in", "dst")):
        each = arcs.groupBy("elabel", end).agg(F.count("*").alias("d"))
        ends = F.array(*[F.sum((F.col("d") >= k).cast("long")) for k in range(1, STEPS + 1)])
        parts.append(each.groupBy("elabel").agg(F.sum("d").alias("arcs"), F.max("d").alias("top"), ends.alias("ends")).select(F.lit(side).alias("side"), F.col("elabel").alias("kind"), "arcs", "top", "ends"))
    rows = parts[0].unionByName(parts[1]).unionByName(parts[2]).limit(3 * MOST_LABELS + 1).collect()
    if len(rows) > 3 * MOST_LABELS:
        return None
    sides = [r for r in rows if r.side]
    return GraphStats(
        {r.kind: r.arcs for r in rows if not r.side}, {r.kind: r.arcs for r in sides if r.side == "out"},
        {(r.kind, r.side): tuple(r.ends) for r in sides}, {(r.kind, r.side): r.top for r in sides},
    )


@dataclass(frozen=True)
class MatchSpec:
    """How a query is matched.

    `filters_skipped_at`: filters are left out where the graph's statistics say that they would keep
    at least this share of every candidate set (None: never). `lazy`: a bundle that depends on one
    pinned place is only defined, and held when it is cut or asked for. `share`: "estimate" shares
    an extension where keys should be at most half of the rows, "always" wherever its keys are fewer
    columns. `guarded`: size pruning only counts vertices whose candidates provably lie inside.
    """

    semantics: str = "iso"  # iso, hom, induced
    engine: str = "levels"  # levels, batched, kernel, region
    filters: tuple[str, ...] = ("label", "degree", "nlf", "arc")
    arc_passes: int = 1
    order: str | tuple[int, ...] = "candidate_ratio"
    colouring: str | tuple[bool, ...] = "risk"
    reuse: str | None = "bn"  # bn, dep, or None
    share: str = "estimate"  # estimate, always
    prune_dominated: bool = True
    guarded: bool = True
    prune_failing: bool = True
    injectivity: str = "eager"  # eager, singleton, late
    split_case3: bool = False
    lazy: bool = True
    limit: int | None = None
    timeout_s: float | None = None
    batches: int = 8
    filters_skipped_at: float | None = 0.8
    kernel_arcs: int = 3_000_000  # largest index that the kernel may broadcast
    broadcast_arcs: int = 200_000  # most pairs of a link that a join may broadcast
    bundle_most: int = 65_536  # longest array of a bundle; longer ones are cut by a hash

    def but(self, **changes) -> "MatchSpec":
        return replace(self, **changes)


@dataclass(frozen=True)
class MatchPlan:
    """All that is decided before the search; positions are places in the order."""

    query: QueryGraph
    order: tuple[int, ...]
    bundled: tuple[bool, ...]
    counts: tuple[int, ...]
    back: tuple[tuple[int, ...], ...]
    depends: tuple[frozenset[int], ...]
    anchor: tuple[int, ...]
    reusable: tuple[bool, ...]
    dominated: tuple[frozenset[int], ...]
    need: tuple[int, ...] = field(default=())

    def back_pinned(self, i: int) -> list[int]:
        return [j for j in self.back[i] if not self.bundled[j]]

    def back_bundled(self, i: int) -> list[int]:
        return [j for j in self.back[i] if self.bundled[j]]

    def case(self, i: int) -> int:
        """1 pinned over pinned, 2 bundled over pinned, 3 pinned over bundled, 4 bundled over bundled."""
        over = any(self.bundled[j] for j in self.back[i])
        return (2 if over else 0) + (2 if self.bundled[i] else 1)

    def clash(self, i: int, j: int) -> bool:
        return self.query.may_clash(self.order[i], self.order[j])

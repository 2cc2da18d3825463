"""The whole way: filter, order, colour, enumerate."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import MatchPlan, MatchSpec, PropertyGraph, QueryGraph
from ..plans.analysis import make_plan
from . import expand
from .filters import by_label, candidate_table, counts_by_stats, filter_masks
from .index import CandidateIndex
from .levels import Frontier, enumerate_packed, hold, level_counters


@dataclass
class MatchResult:
    """Packed matches with the plan that made them; nothing runs before it is asked for."""

    graph: PropertyGraph
    plan: MatchPlan
    spec: MatchSpec
    frontiers: list[Frontier]
    index: CandidateIndex
    cand: list[DataFrame]
    metrics: dict = field(default_factory=dict)

    @property
    def levels(self) -> list[DataFrame]:
        """The frontiers with every bundle as an array."""
        return [hold(f, self.index, self.plan, self.spec).df for f in self.frontiers]

    @property
    def packed(self) -> DataFrame:
        return hold(self.frontiers[-1], self.index, self.plan, self.spec).df

    def flat(self) -> DataFrame:
        """One row a match, columns named as in the query; with a limit, root batch by root batch."""
        if self.spec.limit is not None and self.spec.engine in ("levels", "batched"):
            from .batched import batches_of

            return batches_of(self.graph, self.plan, self.cand, self.index, self.spec)[0]
        out = expand.named(expand.flat(self.frontiers[-1], self.index, self.plan, self.spec.semantics), self.plan)
        if self.spec.semantics == "induced":
            out = induced_only(out, self.graph, self.plan.query)
        return out if self.spec.limit is None else out.limit(self.spec.limit)

    def _by_rows(self) -> bool:
        return self.spec.semantics == "induced" or self.spec.limit is not None

    def _places(self, names: tuple[str, ...]) -> list[int]:
        return [self.plan.order.index(self.plan.query.names.index(n)) for n in names]

    def count(self) -> DataFrame:
        if self._by_rows():
            return self.flat().agg(F.count("*").alias("n"))
        return expand.count(self.frontiers[-1], self.index, self.plan, self.spec.semantics)

    def count_by(self, *names: str) -> DataFrame:
        """Some columns and n, the matches that have them; other bundles are counted, not exploded."""
        if self._by_rows():
            return self.flat().groupBy(*names).agg(F.count("*").alias("n"))
        places = self._places(names)
        rows = expand.counted(self.frontiers[-1], self.index, self.plan, self.spec.semantics, places)
        return rows.select(*[F.col(f"q{p}").alias(n) for p, n in zip(places, names)], "n")

    def select(self, *names: str, distinct: bool = False) -> DataFrame:
        """Some columns of the matches, once for each match or each once."""
        if not distinct or self._by_rows():
            out = self.flat().select(*names)
            return out.distinct() if distinct else out
        places = self._places(names)
        rows = expand.distinct_images(self.frontiers[-1], self.index, self.plan, self.spec.semantics, places)
        return rows.select(*[F.col(f"q{p}").alias(n) for p, n in zip(places, names)])

    def counters(self) -> DataFrame:
        return level_counters(self.levels, self.plan)

    def write(self, path: str, packed: bool = True, buckets: int = 64) -> None:
        """Parquet, partitioned by a hash of the first column; packed by default."""
        df = self.packed if packed else self.flat()
        df.withColumn("bucket", F.pmod(F.hash(df.columns[0]), F.lit(buckets))).write.partitionBy("bucket").parquet(path)


def induced_only(matches: DataFrame, g: PropertyGraph, q: QueryGraph) -> DataFrame:
    """Keeps matches in which vertices that the query does not link are not linked either: each match
    names its unlinked pairs, which meet the arcs in one join however many they are."""
    links = set(q.links())
    pairs = [(a, b) for a in range(q.n) for b in range(a + 1, q.n) if (a, b) not in links]
    if not pairs:
        return matches
    both = [(x, y) for a, b in pairs for x, y in (((a, b), (b, a)) if q.directed else ((a, b),))]
    asked = F.explode(F.array(*[F.struct(F.col(q.names[x]).alias("s"), F.col(q.names[y]).alias("d")) for x, y in both]))
    arcs = g.edges.select(F.col("src").alias("__s"), F.col("dst").alias("__d")).distinct()
    wrong = matches.withColumn("__p", asked).join(arcs.hint("merge"), (F.col("__p.s") == F.col("__s")) & (F.col("__p.d") == F.col("__d")), "left_semi")
    return matches.join(wrong.select(*q.names).distinct().hint("merge"), list(q.names), "left_anti").select(*q.names)


def candidate_counts(cand: list[DataFrame]) -> list[int]:
    """Sizes of the candidate sets: one small round trip to the driver."""
    found = {r.q: r["count"] for r in candidate_table(cand).groupBy("q").count().collect()}
    return [found.get(i, 0) for i in range(len(cand))]


def prepare(g: PropertyGraph, q: QueryGraph, spec: MatchSpec) -> tuple[MatchPlan, list[DataFrame], CandidateIndex]:
    """Filter, order, colour and index; the arcs, candidates and index are stored tables.

    Filters that the graph's statistics show to be idle are left out; the candidates of a vertex are
    then all vertices of its label, and the index is the graph's own arcs.
    """
    g = g.store()
    counts, masks = counts_by_stats(g, q, spec), None
    if counts is not None:
        cand = [by_label(g, q, i) for i in range(q.n)]
        inside = lambda i, j: q.labels[i] == q.labels[j]
    else:
        masks = filter_masks(g, q, spec)
        same = [(i, j) for i in range(q.n) for j in range(q.n) if i != j and q.labels[i] == q.labels[j]]
        counts, known = masks.counts(same if spec.prune_dominated and spec.semantics != "hom" else [])
        cand = [masks.ids(i) for i in range(q.n)]
        inside = lambda i, j: known.get((i, j), False)
    first = make_plan(q, counts, spec.but(prune_dominated=False))
    if not spec.prune_dominated or spec.semantics == "hom":
        plan = first
    else:
        by_place = (lambda i, j: inside(first.order[i], first.order[j])) if spec.guarded else None
        plan = make_plan(q, counts, spec, by_place)
    return plan, cand, CandidateIndex(g, plan, masks, spec)


def match(g: PropertyGraph, q: QueryGraph, spec: MatchSpec = MatchSpec()) -> MatchResult:
    """All matches of q in g. All engines give packed rows; a kernel whose index is
    too large to be broadcast searches regions instead, or level by level.

    A query vertex without candidates gives an empty result of the right columns. A disconnected
    query is a product of its components.
    """
    if q.n == 0:
        raise ValueError("the query has no vertex")
    g, began = g.store(), time.time()
    plan, cand, index = prepare(g, q, spec)
    metrics = {"counts": plan.counts, "pre_ms": (time.time() - began) * 1e3}
    if spec.engine == "kernel":
        from .kernel import kernel_packed

        packed = kernel_packed(index, plan, spec, cand)
        if packed is not None:
            return MatchResult(g, plan, spec, [Frontier(packed)], index, cand, metrics)
    if spec.engine == "region" or (spec.engine == "kernel" and not plan.bundled[0] and len(q.components()) == 1):
        from .kernel import region_packed

        return MatchResult(g, plan, spec, [Frontier(region_packed(index, plan, spec, cand))], index, cand, metrics)
    if spec.engine == "batched":
        from .batched import batches_of

        return MatchResult(g, plan, spec, [batches_of(g, plan, cand, index, spec, packed=True)[0]], index, cand, metrics)
    frontiers = enumerate_packed(index, plan, spec, cand) if spec.limit is None else [Frontier(cand[plan.order[0]])]
    return MatchResult(g, plan, spec, frontiers, index, cand, metrics)

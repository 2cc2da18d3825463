"""The candidate index: for each query link, which candidates of one end go with which of the other."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.scratch import written
from ..model import MatchPlan, MatchSpec, PropertyGraph
from .filters import Masks, arcs_of, has_bit, marked_arcs, words


class CandidateIndex:
    """Pairs of candidates by link of two places, and sorted neighbour lists made from them on demand.

    With filtered candidates the pairs are one table of arcs, each with a mask of the query arcs
    that it may stand for; where filters were left out they are the graph's own stored arcs.
    """

    def __init__(self, g: PropertyGraph, plan: MatchPlan, masks: Masks | None, spec: MatchSpec = MatchSpec()):
        self.g, self.plan, self.spec = g, plan, spec
        self.spark = g.edges.sparkSession
        q, at = plan.query, {u: i for i, u in enumerate(plan.order)}
        #: arcs of each link of places i < j: (number of the query arc, does it lead from i to j)
        self.arcs = {tuple(sorted((at[u], at[w]))): [(k, at[q.edges[k][0]] < at[q.edges[k][1]]) for k in ks] for (u, w), ks in q.link_arcs().items()}
        self.marks, self._lists = None, {}
        stats = g.stats
        self.sizes = {k: None if stats is None else sum(stats.arcs.values()) if e is None else stats.arcs.get(e, 0) for k, (_, _, e) in enumerate(q.edges)}
        if masks is not None and self.arcs:
            self.marks = written(marked_arcs(g, q, masks), "index")
            ks = [k for found in self.arcs.values() for k, _ in found]
            row = self.marks.agg(*[F.coalesce(F.sum(has_bit("a", k).cast("long")), F.lit(0)).alias(f"n{k}") for k in ks]).first()
            self.sizes = {k: row[f"n{k}"] for k in ks}

    def links(self) -> list[tuple[int, int]]:
        return list(self.arcs)

    def _arc(self, k: int) -> DataFrame:
        if self.marks is None:
            return arcs_of(self.g, self.plan.query.edges[k][2])
        return self.marks.where(has_bit("a", k)).select("src", "dst")

    def pairs(self, i: int, j: int) -> DataFrame:
        """va (candidate of place i), vb (candidate of place j)."""
        lo, hi = min(i, j), max(i, j)
        found = None
        for k, onward in self.arcs[lo, hi]:
            va, vb = ("src", "dst") if onward == (i < j) else ("dst", "src")
            one = self._arc(k).select(F.col(va).alias("va"), F.col(vb).alias("vb"))
            found = one if found is None else found.join(one, ["va", "vb"], "left_semi")
        return found

    def size(self, i: int, j: int) -> int | None:
        """At most this many pairs."""
        known = [self.sizes[k] for k, _ in self.arcs[min(i, j), max(i, j)]]
        return None if None in known else min(known)

    def total(self) -> int | None:
        sizes = [self.size(*link) for link in self.arcs]
        return None if None in sizes else sum(sizes)

    def top(self, i: int, j: int) -> int | None:
        """No list of candidates of place j next to one of place i is longer; None if not known."""
        stats = self.g.stats
        best = None
        for k, onward in self.arcs[min(i, j), max(i, j)]:
            e = self.plan.query.edges[k][2]
            side = "out" if onward == (i < j) else "in"
            if stats is None or (e is None and len(stats.arcs) != 1):
                continue
            found = stats.top.get((e if e is not None else next(iter(stats.arcs)), side), 0)
            best = found if best is None else min(best, found)
        return best

    def mean(self, i: int, j: int) -> float:
        """About how many candidates of place j go with one of place i."""
        size = self.size(i, j)
        return float("inf") if size is None else size / max(1, self.plan.counts[self.plan.order[i]])

    def single(self, i: int, j: int) -> bool:
        """Has no candidate of place i more than one neighbour among those of j?"""
        return self.top(i, j) == 1

    def parts(self, j: int) -> int:
        """Into how many parts lists of candidates of place j are cut, so that none grows with a hub."""
        tops = [self.top(*((a, b) if b == j else (b, a))) for a, b in self.arcs if j in (a, b)]
        if None in tops:
            return 1
        return max([-(-t // self.spec.bundle_most) for t in tops] or [1]) or 1

    def lists(self, i: int, j: int) -> DataFrame:
        """va, part, nbrs: sorted distinct candidates of place j next to each candidate of place i, in
        parts by a hash of the candidate where lists would be long."""
        if (i, j) not in self._lists:
            n = self.parts(j)
            part = F.pmod(F.xxhash64("vb"), F.lit(n)).cast("int") if n > 1 else F.lit(0)
            self._lists[i, j] = self.pairs(i, j).groupBy("va", part.alias("part")).agg(F.array_sort(F.collect_list("vb")).alias("nbrs"))
        return self._lists[i, j]

    def degrees(self, i: int, j: int) -> DataFrame:
        """va, d: how many candidates of place j are next to each candidate of place i."""
        return self.pairs(i, j).groupBy("va").agg(F.count("*").alias("d"))

    def near(self, df: DataFrame, i: int, j: int) -> DataFrame:
        """df, made of the pairs of a link, as the right side of a join: broadcast if they are few,
        else sorted and merged, since the size of a frontier's files says little about its rows."""
        size = self.size(i, j)
        return F.broadcast(df) if size is not None and size <= self.spec.broadcast_arcs else df.hint("merge")

    def signature(self, w: int, j: int) -> tuple | None:
        """Equal for two places whose lists next to place w are surely equal."""
        if self.marks is not None:
            return None
        q = self.plan.query
        kinds = sorted((str(q.edges[k][2]), onward == (w < j)) for k, onward in self.arcs[min(w, j), max(w, j)])
        return w, tuple(kinds), q.labels[self.plan.order[j]]

    def table(self) -> DataFrame:
        """qa, qb, va, vb: the whole index, both directions, by query vertex."""
        both = [(a, b) for i, j in self.arcs for a, b in ((i, j), (j, i))]
        return reduce(DataFrame.unionByName, [self.pairs(a, b).select(F.lit(self.plan.order[a]).alias("qa"), F.lit(self.plan.order[b]).alias("qb"), "va", "vb") for a, b in both])

    def links_table(self) -> DataFrame:
        """link (i * 64 + j), va, vb: each pair once."""
        return reduce(DataFrame.unionByName, [self.pairs(i, j).select(F.lit(i * 64 + j).alias("link"), "va", "vb") for i, j in self.arcs])

    def save(self, name: str, buckets: int = 64) -> None:
        """Tables name_i_j bucketed and sorted by va, so that joins on va need no shuffle of theirs."""
        for a, b in [(a, b) for i, j in self.arcs for a, b in ((i, j), (j, i))]:
            self.pairs(a, b).write.bucketBy(buckets, "va").sortBy("va").mode("overwrite").saveAsTable(f"{name}_{a}_{b}")

    def load(self, name: str) -> "CandidateIndex":
        """The same index, read from the tables that `save` wrote."""
        other = SavedIndex.__new__(SavedIndex)
        other.__dict__.update(self.__dict__ | {"name": name, "_lists": {}})
        return other


class SavedIndex(CandidateIndex):
    """An index over bucketed tables."""

    def pairs(self, i: int, j: int) -> DataFrame:
        return self.spark.table(f"{self.name}_{i}_{j}")


__all__ = ["CandidateIndex", "SavedIndex", "words"]

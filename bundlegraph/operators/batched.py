"""Root batches: bounded frontiers, early stop at a limit or a deadline, and dead keys left out."""

from __future__ import annotations

import time
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.scratch import written
from ..model import MatchPlan, MatchSpec, PropertyGraph, QueryGraph
from ..plans.analysis import closed
from . import expand
from .index import CandidateIndex
from .levels import Frontier, enumerate_packed, extend, hold, seed


class NogoodStore:
    """Keys of a level that had no completion in an earlier batch; later batches leave them out.

    A key holds a set of columns that is closed under what the rest of the search reads of them
    (so it decides alone that the level dies). It is recorded at the places where the search of a
    batch lost rows; tables of up to `most` keys are broadcast, larger ones joined by a shuffle.
    """

    def __init__(self, plan: MatchPlan, most: int = 200_000):
        self.plan, self.most, self.dead = plan, most, {}

    def columns(self, i: int) -> list[str]:
        """Key of level i (places below i) for a failure to place i: back-neighbours, closed."""
        places = closed(set(self.plan.back[i]), i, list(self.plan.back), self.plan.bundled)
        return [f"q{j}" for j in sorted(places) if j < i]

    def apply(self, frontier: DataFrame, i: int) -> DataFrame:
        if i not in self.dead:
            return frontier
        keys, n = self.dead[i]
        return frontier.join(F.broadcast(keys) if n <= self.most else keys.hint("merge"), self.columns(i), "left_anti")

    def record(self, frontier: DataFrame, extended: DataFrame, i: int) -> None:
        """Keys of the frontier that the extension (before conflicts) has no row for."""
        cols = self.columns(i)
        if len(cols) >= i or not cols:
            return
        gone = frontier.select(*cols).distinct().join(extended.select(*cols).distinct(), cols, "left_anti")
        held = written(gone if i not in self.dead else self.dead[i][0].unionByName(gone).distinct(), "nogoods")
        self.dead[i] = held, held.count()


def batches_of(
    g: PropertyGraph, plan: MatchPlan, cand: list[DataFrame], index: CandidateIndex, spec: MatchSpec, nogoods: bool = False, packed: bool = False,
) -> tuple:
    """Flat matches, at most `spec.limit` (packed: a frontier of all), and what happened: batches run,
    rows, whether time ran out.

    Each batch takes the roots of one hash class and all its levels run as one plan; a batch is
    written to the shared folder. With a limit, the first batch holds few roots and each next one four
    times as many, so a small limit costs a small batch.
    """
    began, parts, rows, timed_out, ran = time.time(), [], 0, False, 0
    pins = NogoodStore(plan) if nogoods and not any(plan.bundled) else None
    share, edges, at = 1 / spec.batches, [], 0.0
    if spec.limit is not None:
        share = max(1e-6, min(1.0, spec.limit / max(1, plan.counts[plan.order[0]]) / 4))
    while at < 1.0 - 1e-9:
        edges.append((at, min(1.0, at + share)))
        at, share = edges[-1][1], share if spec.limit is None else share * 4
    room = 1 << 30
    for lo, hi in edges:
        if spec.timeout_s is not None and time.time() - began > spec.timeout_s:
            timed_out = True
            break
        draw = F.pmod(F.xxhash64("id", F.lit("root")), F.lit(room))
        roots = cand[plan.order[0]].where((draw >= int(lo * room)) & (draw < (room if hi >= 1 else int(hi * room))))
        if pins:
            level = seed(roots, plan).df
            for i in range(1, plan.query.n):
                level = pins.apply(level, i)
                nxt = extend(Frontier(level), index, plan, i, spec.but(injectivity="late", lazy=False), cand[plan.order[i]]).df
                pins.record(level, nxt, i)
                level = written(nxt, "batch")
            fr = Frontier(level)
        else:
            fr = enumerate_packed(index, plan, spec, cand, roots)[-1]
        if packed:
            parts.append(written(hold(fr, index, plan, spec).df, "packed"))
        else:
            flat = expand.named(expand.flat(fr, index, plan, spec.semantics), plan)
            if spec.semantics == "induced":
                from .match import induced_only

                flat = induced_only(flat, g, plan.query)
            parts.append(written(flat if spec.limit is None else flat.limit(spec.limit - rows), "matches"))
        rows += parts[-1].count()
        ran += 1
        if spec.limit is not None and rows >= spec.limit:
            break
    facts = {"batches": ran, "rows": rows, "timed_out": timed_out, "counts": plan.counts, "ms": (time.time() - began) * 1e3}
    if packed:
        none = hold(enumerate_packed(index, plan, spec, cand)[-1], index, plan, spec).df.limit(0) if not parts else None
        return Frontier(reduce(DataFrame.unionByName, parts) if parts else none), facts
    if not parts:
        parts = [g.vertices.sparkSession.createDataFrame([], ", ".join(f"`{n}` long" for n in plan.query.names))]
    return reduce(DataFrame.unionByName, parts), facts


def batched(g: PropertyGraph, q: QueryGraph, spec: MatchSpec = MatchSpec(), nogoods: bool = False) -> tuple[DataFrame, dict]:
    """Flat matches by root batches, and what happened; `pre_ms` is the time of filter, order and index."""
    from .match import prepare

    g, began = g.store(), time.time()
    plan, cand, index = prepare(g, q, spec.but(prune_dominated=spec.prune_dominated and spec.semantics != "hom"))
    pre = (time.time() - began) * 1e3
    found, facts = batches_of(g, plan, cand, index, spec, nogoods)
    return found, facts | {"pre_ms": pre}

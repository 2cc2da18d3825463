"""Candidate sets: which data vertices may stand for each query vertex.

All sets are held in one table of bit masks: a row is a data vertex, bit u says that it may stand
for query vertex u. So every condition of every query vertex is tested in one pass over the
vertices, and a pass of arc consistency is two joins and one aggregate, however large the query is.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.scratch import written
from ..model import STEPS, GraphStats, MatchSpec, PropertyGraph, QueryGraph

#: Bits of a mask column; larger queries have several columns.
WORD = 62


def words(n: int) -> int:
    return -(-n // WORD) or 1


def has_bit(prefix: str, i: int) -> Column:
    return F.col(f"{prefix}{i // WORD}").bitwiseAND(F.lit(1 << i % WORD)) != 0


def bits(tests: list[Column], prefix: str) -> list[Column]:
    """One mask column for each WORD tests."""
    out = []
    for w in range(words(len(tests))):
        part = [F.when(t, F.lit(1 << k).cast("long")).otherwise(F.lit(0).cast("long")) for k, t in enumerate(tests[w * WORD : (w + 1) * WORD])]
        out.append(reduce(lambda a, b: a.bitwiseOR(b), part, F.lit(0).cast("long")).alias(f"{prefix}{w}"))
    return out


def any_bit(prefix: str, n: int) -> Column:
    return reduce(lambda a, b: a | b, [F.col(f"{prefix}{w}") != 0 for w in range(words(n))])


def arcs_of(g: PropertyGraph, elabel: str | None, test: str | None = None) -> DataFrame:
    """src, dst of one kind of arc, each once, without loops."""
    e = g.edges.where("src <> dst")
    e = e if elabel is None else e.where(F.col("elabel") == elabel)
    e = e.where(test) if test else e
    one = g.stored and not g.properties and (elabel is not None or (g.stats is not None and len(g.stats.arcs) <= 1))
    return e.select("src", "dst") if one else e.select("src", "dst").distinct()


def by_label(g: PropertyGraph, q: QueryGraph, i: int) -> DataFrame:
    """id: vertices of the label of query vertex i."""
    v = g.vertices if q.labels[i] is None else g.vertices.where(F.col("label") == q.labels[i])
    return v.select("id").where("id IS NOT NULL")


def sides(q: QueryGraph, i: int) -> dict[tuple[str, str | None], list[int]]:
    """Neighbours of i by (out or in, edge label). In an undirected graph every arc counts as out."""
    out: dict[tuple[str, str | None], list[int]] = {}
    for a, b, e in q.edges:
        if a != b and i in (a, b):
            out.setdefault(("out" if a == i or not q.directed else "in", e), []).append(b if a == i else a)
    return {k: sorted(set(v)) for k, v in out.items()}


@dataclass
class Masks:
    """df: id and mask columns m0, m1, ...; only vertices with a bit."""

    df: DataFrame
    q: QueryGraph

    def ids(self, i: int) -> DataFrame:
        return self.df.where(has_bit("m", i)).select("id")

    def stored(self) -> "Masks":
        return Masks(written(self.df, "masks"), self.q)

    def counts(self, pairs: list[tuple[int, int]] = ()) -> tuple[list[int], dict[tuple[int, int], bool]]:
        """Sizes of the sets and, for each pair (i, j), whether set j lies inside set i: one small row."""
        size = [F.coalesce(F.sum(has_bit("m", i).cast("long")), F.lit(0)) for i in range(self.q.n)]
        outside = [F.coalesce(F.sum((has_bit("m", j) & ~has_bit("m", i)).cast("long")), F.lit(0)) for i, j in pairs]
        row = self.df.agg(F.array(*size).alias("n"), F.array(*outside, F.lit(0).cast("long")).alias("out")).first()
        return list(row.n), {p: row.out[k] == 0 for k, p in enumerate(pairs)}


def _profile(g: PropertyGraph, side: str, elabel: str | None, labels: list[str], name: str) -> DataFrame:
    """id, {name}d neighbours on a side, and how many of each label: one aggregate for all query vertices."""
    a = arcs_of(g, elabel)
    a = a.select(F.col("src").alias("id"), F.col("dst").alias("near")) if side == "out" else a.select(F.col("dst").alias("id"), F.col("src").alias("near"))
    sums = [F.count("*").alias(f"{name}d")]
    if labels:
        near = g.vertices.where(F.col("label").isin(labels)).select(F.col("id").alias("near"), F.col("label").alias("near_label")).distinct()
        a = a.join(near, "near", "left")
        sums += [F.sum((F.col("near_label") == lab).cast("long")).alias(f"{name}l{k}") for k, lab in enumerate(labels)]
    return a.groupBy("id").agg(*sums)


def base_masks(g: PropertyGraph, q: QueryGraph, spec: MatchSpec) -> Masks:
    """Labels, predicates and loops, then degrees and neighbour labels as far as spec.filters names them.

    Degree: at least as many distinct neighbours as the query vertex, by side and edge label (not
    for homomorphisms). Neighbour labels: at least as many of each label as the query vertex has
    (homomorphisms: one).
    """
    iso = spec.semantics != "hom"
    rows = g.vertices.where("id IS NOT NULL")
    if all(lab is not None for lab in q.labels):
        rows = rows.where(F.col("label").isin(sorted(set(q.labels))))
    tests: list[Column] = []
    loops: dict[str | None, str] = {}
    need: dict[tuple[str, str | None], dict[str, None]] = {}
    # a pass along the arcs asks for one neighbour anyway
    counted = lambda near: iso and len(near) > 1 if "arc" in spec.filters else True
    for i in range(q.n):
        for e in q.loops(i):
            loops.setdefault(e, f"__loop{len(loops)}")
        for key, near in sides(q, i).items():
            asked = [q.labels[w] for w in near if q.labels[w] is not None] if "nlf" in spec.filters else []
            if counted(near) and (asked or ("degree" in spec.filters and iso)):
                need.setdefault(key, {}).update(dict.fromkeys(asked))
    for e, name in loops.items():
        at = g.edges.where("src = dst") if e is None else g.edges.where((F.col("src") == F.col("dst")) & (F.col("elabel") == e))
        rows = rows.join(at.select(F.col("src").alias("id"), F.lit(True).alias(name)).distinct(), "id", "left")
    profiles: dict[tuple[str, str | None], tuple[str, list[str]]] = {}
    for k, (key, labels) in enumerate(need.items()):
        profiles[key] = (f"__p{k}", sorted(labels))
        rows = rows.join(_profile(g, *key, sorted(labels), f"__p{k}"), "id", "left")
    for i in range(q.n):
        test = F.lit(True) if q.labels[i] is None else F.col("label") == q.labels[i]
        if q.where and q.where[i]:
            test = test & F.expr(q.where[i])
        for e in q.loops(i):
            test = test & F.col(loops[e])
        for key, near in sides(q, i).items():
            if key not in profiles or not counted(near):
                continue
            name, labels = profiles[key]
            if "degree" in spec.filters and iso:
                test = test & (F.col(f"{name}d") >= len(near))
            asked = [q.labels[w] for w in near if q.labels[w] is not None] if "nlf" in spec.filters else []
            for lab in set(asked):
                test = test & (F.col(f"{name}l{labels.index(lab)}") >= (asked.count(lab) if iso else 1))
        tests.append(F.coalesce(test, F.lit(False)))
    masked = rows.select("id", *bits(tests, "m")).where(any_bit("m", q.n))
    merged = masked.groupBy("id").agg(*[F.bit_or(f"m{w}").alias(f"m{w}") for w in range(words(q.n))])
    return Masks(merged, q)


def marked_arcs(g: PropertyGraph, q: QueryGraph, masks: Masks, near=None) -> DataFrame:
    """src, dst, a0, ...: the arcs that may stand for a query arc; bit k says that it may for arc k."""
    e = g.edges.where("src <> dst")
    kinds = {lab for _, _, lab in q.edges}
    if None not in kinds:
        e = e.where(F.col("elabel").isin(sorted(kinds)))
    hint = near or (lambda df: df)
    cols = [f"m{w}" for w in range(words(q.n))]
    for end, name in (("src", "s"), ("dst", "d")):
        side = masks.df.select(F.col("id").alias(end), *[F.col(c).alias(f"{name}{c[1:]}") for c in cols])
        e = e.join(hint(side), end)
    tests = []
    for k, (a, b, lab) in enumerate(q.edges):
        test = F.lit(a != b) if lab is None else F.lit(a != b) & (F.col("elabel") == lab)
        if q.edge_test(k):
            test = test & F.expr(q.edge_test(k))
        tests.append(F.coalesce(test & has_bit("s", a) & has_bit("d", b), F.lit(False)))
    out = e.select("src", "dst", *bits(tests, "a")).where(any_bit("a", len(tests)))
    if g.properties or not g.stats or len(g.stats.arcs) > 1:  # an arc may come in several kinds
        out = out.groupBy("src", "dst").agg(*[F.bit_or(f"a{w}").alias(f"a{w}") for w in range(words(len(tests)))])
    return out


def arc_pass(g: PropertyGraph, q: QueryGraph, masks: Masks) -> Masks:
    """One pass of arc consistency: a candidate needs a candidate neighbour along every query arc."""
    if not any(a != b for a, b, _ in q.edges):
        return masks
    arcs, n = marked_arcs(g, q, masks), words(len(q.edges))
    zero = [F.lit(0).cast("long")] * n
    # one row for each end: what arcs it can begin (o) and end (i)
    ends = arcs.select(F.explode(F.array(
        F.struct(F.col("src").alias("id"), *[F.col(f"a{w}").alias(f"o{w}") for w in range(n)], *[z.alias(f"i{w}") for w, z in enumerate(zero)]),
        F.struct(F.col("dst").alias("id"), *[z.alias(f"o{w}") for w, z in enumerate(zero)], *[F.col(f"a{w}").alias(f"i{w}") for w in range(n)]),
    )).alias("x")).select("x.*")
    met = ends.groupBy("id").agg(*[F.bit_or(f"{s}{w}").alias(f"{s}{w}") for s in "oi" for w in range(n)])
    rows, tests = masks.df.join(met, "id", "left"), []
    for u in range(q.n):
        test = has_bit("m", u)
        for k, (a, b, _) in enumerate(q.edges):
            if a != b and u in (a, b):
                test = test & F.coalesce(has_bit("o" if a == u else "i", k), F.lit(False))
        tests.append(test)
    return Masks(rows.select("id", *bits(tests, "m")).where(any_bit("m", q.n)), q)


def filter_masks(g: PropertyGraph, q: QueryGraph, spec: MatchSpec) -> Masks:
    masks = base_masks(g, q, spec).stored()
    if "arc" in spec.filters:
        for _ in range(spec.arc_passes):
            masks = arc_pass(g, q, masks).stored()
    return masks


def filter_candidates(g: PropertyGraph, q: QueryGraph, spec: MatchSpec = MatchSpec()) -> list[DataFrame]:
    """One table (id) for each query vertex, a superset of its images in any match."""
    masks = filter_masks(g.store(), q, spec)
    return [masks.ids(i) for i in range(q.n)]


def refine_to_fixpoint(g: PropertyGraph, q: QueryGraph, masks: Masks, least_shrink: float = 0.01, most: int = 10) -> tuple[Masks, list[int]]:
    """Arc passes until a pass removes less than `least_shrink` of the candidates. Also the totals seen."""
    totals = [sum(masks.counts()[0])]
    for _ in range(most):
        masks = arc_pass(g, q, masks).stored()
        totals.append(sum(masks.counts()[0]))
        if totals[-2] - totals[-1] <= least_shrink * totals[-2]:
            break
    return masks, totals


def counts_by_stats(g: PropertyGraph, q: QueryGraph, spec: MatchSpec) -> list[int] | None:
    """Sizes of the candidate sets if filters may be left out, else None.

    They may where no vertex or arc has a predicate, each label is implied by the kinds of the arcs
    at its vertex, and of the vertices with such arcs nearly all have as many as the query asks.
    """
    stats: GraphStats | None = g.stats
    if spec.filters_skipped_at is None or stats is None or any(q.where) or any(q.edge_where) or not q.edges:
        return None
    out = []
    for i in range(q.n):
        near = sides(q, i)
        if q.loops(i) or not near:
            return None
        size = stats.labels.get(q.labels[i], 0) if q.labels[i] is not None else sum(stats.labels.values())
        for (side, e), others in near.items():
            if e is None and len(stats.arcs) != 1:
                return None
            kind = e if e is not None else next(iter(stats.arcs))
            ends = stats.ends.get((kind, side))
            if ends is None:
                return None
            if q.labels[i] is not None and (g.types or {}).get(kind, (None, None))[side == "in"] != q.labels[i]:
                return None
            k = len(others) if spec.semantics != "hom" else 1
            if k > STEPS or ends[k - 1] < spec.filters_skipped_at * ends[0]:
                return None
            size = min(size, ends[k - 1])
        out.append(size)
    return out


def candidate_table(cand: list[DataFrame]) -> DataFrame:
    """q, v: all candidate sets in one table."""
    return reduce(DataFrame.unionByName, [c.select(F.lit(i).alias("q"), F.col("id").alias("v")) for i, c in enumerate(cand)])

"""Level-wise enumeration of packed matches.

A frontier is a table with one column for each placed query vertex: `q{i}` is a long where place
i is pinned and a sorted array of longs where it is bundled. One row stands for all injective
choices from its bundles; rows of a frontier are disjoint.

A bundle that depends on one pinned place alone is left open: its members are the list next to that
place's image, so no array travels with the rows. It is held, as an array, when a later place cuts
or splits it, or when the matches are read. Cutting an open bundle by a pinned image is a join on
single pairs, so only members that survive are ever made.

Extension sets depend on the linked columns alone; where the keys of a level are clearly fewer than
its rows, `extend` computes them on distinct keys and joins them back (`reuse`). Numbers of rows are
estimated from the sizes of candidate sets and links, so no job is spent on the decision.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType

from ..functions.scratch import written
from ..model import MatchPlan, MatchSpec
from .index import CandidateIndex

#: Products of bundle sizes are compared as doubles, which saturate instead of overflowing.
_ONE = 1.0


@dataclass(frozen=True)
class Frontier:
    """df: the placed columns but for the open bundles; rows: about how many, from the graph's statistics.

    A bundled place whose column is no array holds one member in each row: its bundle was cut so far
    that gathering what is left of it would merge next to nothing.
    """

    df: DataFrame
    open: frozenset[int] = frozenset()
    rows: float = 0.0

    def stored(self, name: str) -> "Frontier":
        return Frontier(written(self.df, name), self.open, self.rows)


def _chunked(ids: DataFrame, col: str, chunks: int) -> DataFrame:
    """Bundles of bounded length, dealt by a hash."""
    return ids.groupBy(F.pmod(F.xxhash64(col), F.lit(chunks)).alias("c")).agg(F.array_sort(F.collect_set(col)).alias(col)).select(col)


def _chunks(count: int, most: int) -> int:
    return max(16, -(-2 * count // most))


def seed(cand0: DataFrame, plan: MatchPlan, most: int = 65_536) -> Frontier:
    """The first level: a row for each candidate, or bundles of them if place 0 is bundled."""
    ids, n = cand0.select(F.col("id").alias("q0")), plan.counts[plan.order[0]]
    if not plan.bundled[0]:
        return Frontier(ids, rows=float(n))
    return Frontier(_chunked(ids, "q0", _chunks(n, most)), rows=float(_chunks(n, most)))


def placed(df: DataFrame) -> list[int]:
    return [int(c[1:]) for c in df.columns if c[0] == "q" and c[1:].isdigit()]


def arrays(df: DataFrame) -> set[int]:
    """Places whose column holds a set."""
    return {j for j in placed(df) if isinstance(df.schema[f"q{j}"].dataType, ArrayType)}


def _without(df: DataFrame, plan: MatchPlan, j: int, spec: MatchSpec) -> DataFrame:
    """Takes the single images that it may clash with out of bundle j, or the row if j is one of them."""
    if spec.semantics == "hom" or spec.injectivity != "eager":
        return df
    sets = arrays(df)
    clashing = [p for p in placed(df) if p != j and p not in sets and plan.clash(p, j)]
    if j not in sets:
        return reduce(lambda d, p: d.where(F.col(f"q{j}") != F.col(f"q{p}")), clashing, df)
    if not clashing:
        return df
    left = reduce(lambda x, p: F.array_remove(x, F.col(f"q{p}")), clashing, F.col(f"q{j}"))
    return df.withColumn(f"q{j}", left).where(F.size(f"q{j}") > 0)


def _ordered(df: DataFrame) -> DataFrame:
    return df.select(*[f"q{j}" for j in sorted(placed(df))])


def hold(fr: Frontier, index: CandidateIndex, plan: MatchPlan, spec: MatchSpec, places=None) -> Frontier:
    """The same frontier with open bundles (some, or all and then every bundle) as arrays."""
    df, todo = fr.df, sorted(fr.open if places is None else set(places) & fr.open)
    for j in todo:
        w = plan.back[j][0]
        near = index.lists(w, j).select(F.col("va").alias("__v"), F.col("nbrs").alias(f"q{j}"))
        df = df.join(index.near(near, w, j), F.col(f"q{w}") == F.col("__v")).drop("__v")
        df = _without(df, plan, j, spec)
    if places is None:
        for j in set(placed(df)) - arrays(df):
            df = df.withColumn(f"q{j}", F.array(f"q{j}")) if plan.bundled[j] else df
    return Frontier(_ordered(df), fr.open - set(todo), fr.rows)


def _from_lists(df: DataFrame, index: CandidateIndex, places: list[int], i: int, name: str) -> DataFrame:
    """Adds `name`: the common candidates of place i next to the single images in q{w} of `places`,
    one row for each part that lists of place i come in."""
    for k, w in enumerate(places):
        near = index.lists(w, i).select(F.col("va").alias(f"__v{k}"), F.col("part").alias(f"__t{k}"), F.col("nbrs").alias(f"__n{k}"))
        on = F.col(f"q{w}") == F.col(f"__v{k}")
        if k:
            on = on & (F.col("__t0") == F.col(f"__t{k}"))
        df = df.join(index.near(near, w, i), on).drop(f"__v{k}", *([f"__t{k}"] if k else []))
    both = reduce(F.array_intersect, [F.col(f"__n{k}") for k in range(len(places))])
    return df.withColumn(name, both if len(places) == 1 else F.array_sort(both)).drop("__t0", *[f"__n{k}" for k in range(len(places))])


def set_from_pinned(df: DataFrame, index: CandidateIndex, places: list[int], i: int) -> DataFrame:
    """Adds R, the intersection of the lists of pinned back-neighbours."""
    return _from_lists(df, index, places, i, "R").where(F.size("R") > 0)


def set_from_smallest_bundle(df: DataFrame, index: CandidateIndex, places: list[int], i: int) -> DataFrame:
    """Adds R, the union of the lists of the members of each row's smallest bundle (ties: first place).

    The union is made once for each distinct bundle, with the bundle itself as the key.
    """
    least = F.least(*[F.size(f"q{w}") for w in places]) if len(places) > 1 else F.size(f"q{places[0]}")
    pick = F.coalesce(*[F.when(F.size(f"q{w}") == least, F.struct(F.lit(w).alias("w"), F.col(f"q{w}").alias("b"))) for w in places])
    df = df.withColumn("__p", pick)
    keys = df.select("__p.w", "__p.b").distinct()
    near = reduce(DataFrame.unionByName, [index.lists(w, i).select(F.lit(w).alias("w"), F.col("va").alias("x"), "part", "nbrs") for w in places])
    sets = keys.select("w", "b", F.explode("b").alias("x")).hint("merge").join(near, ["w", "x"]).groupBy("w", "b", "part")
    sets = sets.agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("nbrs")))).alias("R")).hint("merge")
    return df.join(sets, (F.col("__p.w") == sets["w"]) & (F.col("__p.b") == sets["b"])).drop("__p", "w", "b", "part")


def rows_from_pinned(df: DataFrame, index: CandidateIndex, places: list[int], i: int, fresh: list[int] = ()) -> DataFrame:
    """One row for each common candidate x next to the images of `places` (in q{w}) and of `fresh` (in
    n{w}): one join brings candidates, the other links are semi-joins, so no list is held."""
    first, *rest = sorted([*((w, f"q{w}") for w in places), *((w, f"n{w}") for w in fresh)], key=lambda p: index.mean(p[0], i))
    near = index.pairs(first[0], i).select(F.col("va").alias("__v"), F.col("vb").alias("x"))
    df = df.join(index.near(near, first[0], i), F.col(first[1]) == F.col("__v")).drop("__v")
    return reduce(lambda d, p: _linked(d, index, p[0], i, "x", p[1]), rest, df)


def _linked(df: DataFrame, index: CandidateIndex, w: int, i: int, col: str, own: str | None = None) -> DataFrame:
    """Rows whose `col`, a candidate of place i, is next to the image of place w."""
    near = index.pairs(w, i).select(F.col("va").alias("__v"), F.col("vb").alias("__x"))
    return df.join(index.near(near, w, i), (F.col(own or f"q{w}") == F.col("__v")) & (F.col(col) == F.col("__x")), "left_semi")


def _hosts(df: DataFrame, index: CandidateIndex, w: int, i: int, need: int) -> DataFrame:
    """Rows whose image of place w has at least `need` candidates of place i next to it."""
    if need <= 1:
        return df
    enough = index.degrees(w, i).where(F.col("d") >= need).select(F.col("va").alias(f"q{w}"))
    return df.join(index.near(enough, w, i), f"q{w}", "left_semi")


#: Rows that hold the same x are gathered if that leaves less than this share of them.
MERGES_BELOW = 0.5
#: Sets that are expected to have no more members than this are made as rows of one member each.
FEW = 1.4


def expected(index: CandidateIndex, plan: MatchPlan, i: int, places: list[int]) -> float:
    """About how many candidates of place i go with one image of each of `places`."""
    first, *rest = sorted(index.mean(w, i) for w in places)
    return reduce(lambda x, m: x * min(1.0, m / max(1, plan.counts[plan.order[i]])), rest, first)


def _spread(paths: float, bins: float) -> float:
    """Into how many of some bins about so many paths lead."""
    return bins * -math.expm1(-paths / bins) if bins > 0 else 0.0


def rows_from_bundle(df: DataFrame, index: CandidateIndex, plan: MatchPlan, i: int, j: int, is_open: bool) -> DataFrame:
    """Rows (row, x, n{j}): every x next to a member of bundle j with the members next to it.

    Members are gathered by (row, x) only where that is expected to merge rows; else each stands alone.
    """
    cols = df.columns
    size = index.mean(plan.back[j][0], j) if plan.back[j] else float(plan.counts[plan.order[j]])
    if is_open:
        w = plan.back[j][0]
        near = index.pairs(w, j).select(F.col("va").alias("__v"), F.col("vb").alias(f"n{j}"))
        df = df.join(index.near(near, w, j), F.col(f"q{w}") == F.col("__v")).drop("__v")
    else:
        df = df.withColumn(f"n{j}", F.explode(f"q{j}"))
    near = index.pairs(j, i).select(F.col("va").alias("__v"), F.col("vb").alias("x"))
    df = df.join(index.near(near, j, i), F.col(f"n{j}") == F.col("__v")).drop("__v")
    paths = size * index.mean(j, i)
    if index.single(i, j) or _spread(paths, plan.counts[plan.order[i]]) >= MERGES_BELOW * paths:
        return df
    return df.groupBy(*cols, "x").agg(F.array_sort(F.collect_list(f"n{j}")).alias(f"n{j}"))


def cut(df: DataFrame, index: CandidateIndex, plan: MatchPlan, i: int, j: int, is_open: bool, as_set: bool = False) -> DataFrame:
    """Adds n{j}: the members of bundle j next to x, as a set or, if hardly any are expected, as rows of
    one member; rows without one leave."""
    own = [plan.back[j][0]] if plan.back[j] else []
    if index.single(i, j) or (not as_set and own and expected(index, plan, j, [i, *own]) <= FEW):
        near = index.pairs(i, j).select(F.col("va").alias("__v"), F.col("vb").alias(f"n{j}"))
        df = df.join(index.near(near, i, j), F.col("x") == F.col("__v")).drop("__v")
        df = _linked(df, index, plan.back[j][0], j, f"n{j}") if is_open else df.where(F.array_contains(f"q{j}", F.col(f"n{j}")))
        return df.withColumn(f"n{j}", F.array(f"n{j}")) if as_set else df
    near = index.lists(i, j).select(F.col("va").alias("__v"), F.col("part").alias("__t"), F.col("nbrs").alias("__n"))
    df = df.join(index.near(near, i, j), F.col("x") == F.col("__v")).drop("__v")
    if is_open:
        w = plan.back[j][0]
        own = index.lists(w, j).select(F.col("va").alias("__w"), F.col("part").alias("__u"), F.col("nbrs").alias("__o"))
        df = df.join(index.near(own, w, j), (F.col(f"q{w}") == F.col("__w")) & (F.col("__t") == F.col("__u"))).drop("__w", "__u")
    members = F.array_sort(F.array_intersect("__o" if is_open else f"q{j}", "__n"))
    return df.withColumn(f"n{j}", members).drop("__n", "__t", "__o").where(F.size(f"n{j}") > 0)


def _split(df: DataFrame, index: CandidateIndex, i: int, singles: list[int], bundles: list[int], name: str = "x") -> DataFrame:
    """Bundles become single images (n{w}, arrays of one), `name` is the set next to all of them within
    the row's R, which is one part of the whole where lists come in parts."""
    for w in bundles:
        df = df.withColumn(f"__o{w}", F.col(f"q{w}")).withColumn(f"q{w}", F.explode(f"q{w}"))
    df = _from_lists(df, index, sorted(singles + bundles), i, "__set")
    if index.parts(i) > 1:
        df = df.withColumn("__set", F.array_sort(F.array_intersect("__set", "R")))
    df = df.drop("R").withColumnRenamed("__set", name).where(F.size(name) > 0)
    for w in bundles:
        df = df.withColumn(f"n{w}", F.array(f"q{w}")).withColumn(f"q{w}", F.col(f"__o{w}")).drop(f"__o{w}")
    return df


def few(index: CandidateIndex, plan: MatchPlan, i: int, singles: list[int], bundles: list[int], opened: frozenset[int]) -> bool:
    """Is a bundled place expected to have so few images for each choice of its back-neighbours that
    rows of single images cost less than sets? Only asked where sets would have to be made for it."""
    if not plan.bundled[i] or not (len(singles) > 1 or opened & set(bundles)):
        return False
    return expected(index, plan, i, singles + bundles) <= FEW


def extension(
    df: DataFrame, index: CandidateIndex, plan: MatchPlan, i: int, singles: list[int], bundles: list[int], opened: frozenset[int], split_case3: bool = False,
) -> DataFrame:
    """Adds x (image of place i) and n{w} (new bundle of each back-neighbour in `bundles`); `singles`
    are the back-neighbours that hold one image.

    No conflict is checked here, so the result can be shared by rows with other images elsewhere.
    """
    need = plan.need[i] if index.parts(i) == 1 else 1  # a part of a list tells nothing about its whole
    if few(index, plan, i, singles, bundles, opened):
        for w in bundles:
            if w in opened:
                near = index.pairs(plan.back[w][0], w).select(F.col("va").alias("__v"), F.col("vb").alias(f"n{w}"))
                df = df.join(index.near(near, plan.back[w][0], w), F.col(f"q{plan.back[w][0]}") == F.col("__v")).drop("__v")
            else:
                df = df.withColumn(f"n{w}", F.explode(f"q{w}"))
        return rows_from_pinned(df, index, singles, i, bundles)
    if not plan.bundled[i] and not (split_case3 and bundles):  # Cases 1 and 3: one row for each x
        rest = bundles
        if len(singles) > 1 and need > 1:
            df = set_from_pinned(df, index, singles, i).where(F.size("R") >= need).withColumn("x", F.explode("R")).drop("R")
        elif singles:
            df = rows_from_pinned(_hosts(df, index, singles[0], i, need), index, singles, i)
        elif len(bundles) > 1 and not opened & set(bundles):
            df = set_from_smallest_bundle(df, index, bundles, i).where(F.size("R") >= need).withColumn("x", F.explode("R")).drop("R")
        else:
            # open bundles have no size by row: the one that is shortest on average goes first
            j = min(bundles, key=lambda w: index.mean(plan.back[w][0], w) if plan.back[w] else float("inf"))
            df = rows_from_bundle(df, index, plan, i, j, j in opened)
            rest = [w for w in bundles if w != j]
        return reduce(lambda d, w: cut(d, index, plan, i, w, w in opened), rest, df)
    df = set_from_pinned(df, index, singles, i) if singles else set_from_smallest_bundle(df, index, bundles, i)
    df = df.where(F.size("R") >= need)  # the set must also host the places that i dominates
    if not bundles:  # Case 2
        return df.withColumnRenamed("R", "x")
    if not plan.bundled[i]:  # Case 3 the costly way, to compare with: every bundle is split first
        return _split(df, index, i, singles, bundles, "R").withColumn("x", F.explode("R")).drop("R")
    # Case 4: keep the bundles and take x one by one, or split them and keep x as a set
    product = reduce(lambda a, b: a * b, [F.size(f"q{w}").cast("double") for w in bundles], F.lit(_ONE))
    keep = product >= F.size("R")
    kept = df.where(keep).withColumn("x", F.explode("R")).drop("R")
    kept = reduce(lambda d, w: cut(d, index, plan, i, w, False, as_set=True), bundles, kept).withColumn("x", F.array("x"))
    return kept.unionByName(_split(df.where(~keep), index, i, singles, bundles))


def _no_clash(df: DataFrame, plan: MatchPlan, i: int, changed: set[int], spec: MatchSpec) -> DataFrame:
    """Drops rows that use a vertex twice, as far as images tell.

    eager: single images also leave the bundles; singleton: bundles only count once one member is
    left; late: nothing is checked before matches are read.
    """
    if spec.semantics == "hom" or spec.injectivity == "late":
        return df
    for j in placed(df):
        if j == i or not plan.clash(i, j):
            continue
        sets = arrays(df)
        if i not in sets and j not in sets:
            df = df.where(F.col(f"q{i}") != F.col(f"q{j}"))
        elif spec.injectivity == "singleton":
            one = [F.when(F.size(f"q{p}") == 1, F.element_at(f"q{p}", 1)) if p in sets else F.col(f"q{p}") for p in (i, j)]
            df = df.where(F.coalesce(one[0] != one[1], F.lit(True)))
        elif not (i in sets and j in sets):
            p, single = (i, j) if i in sets else (j, i)
            df = df.withColumn(f"q{p}", F.array_remove(f"q{p}", F.col(f"q{single}"))).where(F.size(f"q{p}") > 0)
    return reduce(lambda d, j: _without(d, plan, j, spec), sorted(changed), df)


def key_columns(fr: Frontier, plan: MatchPlan, i: int, spec: MatchSpec) -> list[str]:
    """Columns that the extension at place i reads: linked places (for an open bundle the place that
    defines it), with reuse "dep" all that those depend on."""
    places = set(plan.back[i]) | (plan.depends[i] if spec.reuse == "dep" else set())
    places = {plan.back[j][0] if j in fr.open else j for j in places}
    return [f"q{j}" for j in sorted(places)]


def _grown(fr: Frontier, index: CandidateIndex, plan: MatchPlan, i: int, singles: list[int], bundles: list[int]) -> float:
    """About how many rows the next level has."""
    size = lambda j: index.mean(plan.back[j][0], j) if plan.back[j] else 1.0
    if few(index, plan, i, singles, bundles, fr.open):
        return fr.rows * reduce(lambda x, j: x * size(j), bundles, 1.0) * expected(index, plan, i, singles + bundles)
    if singles:
        each = expected(index, plan, i, singles)
    else:
        each = _spread(min(size(j) * index.mean(j, i) for j in bundles), max(1, plan.counts[plan.order[i]]))
    if plan.bundled[i]:
        return fr.rows * min(1.0, each)
    for j in bundles if singles else []:
        each *= min(1.0, index.mean(i, j) * size(j) / max(1, plan.counts[plan.order[j]]))
    return fr.rows * each


def extend(fr: Frontier, index: CandidateIndex, plan: MatchPlan, i: int, spec: MatchSpec, cand_i: DataFrame) -> Frontier:
    """The next level. Shared extensions: distinct keys are extended once and joined back."""
    if not plan.back[i]:  # a new component of a disconnected query
        ids, n = cand_i.select(F.col("id").alias(f"q{i}")), plan.counts[plan.order[i]]
        rows = _chunks(n, spec.bundle_most) if plan.bundled[i] else n
        ids = _chunked(ids, f"q{i}", rows) if plan.bundled[i] else ids
        return Frontier(_no_clash(_ordered(fr.df.crossJoin(ids)), plan, i, set(), spec), fr.open, fr.rows * rows)
    sets = arrays(fr.df) | fr.open
    singles, bundles = [j for j in plan.back[i] if j not in sets], [j for j in plan.back[i] if j in sets]
    grown = _grown(fr, index, plan, i, singles, bundles)
    if spec.lazy and plan.bundled[i] and not bundles and len(singles) == 1:
        need = plan.need[i] if index.parts(i) == 1 else 1
        return Frontier(_hosts(fr.df, index, singles[0], i, need), fr.open | {i}, fr.rows)
    rows_only = few(index, plan, i, singles, bundles, fr.open)
    if bundles and (plan.bundled[i] or spec.split_case3) and not rows_only:
        fr = hold(fr, index, plan, spec, bundles)
    keys = key_columns(fr, plan, i, spec)
    shares = bool(spec.reuse) and len(keys) < len(fr.df.columns)
    if shares and spec.share != "always":  # are there clearly fewer keys than rows?
        shares = reduce(lambda x, k: x * plan.counts[plan.order[int(k[1:])]], keys, 1.0) <= SHARES_BELOW * fr.rows and not arrays(fr.df.select(*keys))
    twice = not rows_only and bundles and (plan.bundled[i] or (len(bundles) > 1 and not singles and not fr.open & set(bundles)))
    if i > 1 and (shares or twice):
        fr = fr.stored(f"level{i}")  # read more than once
    touched, frontier = fr.open & set(bundles), fr.df
    if not shares:
        out = extension(frontier, index, plan, i, singles, bundles, fr.open, spec.split_case3)
    else:
        ext = extension(frontier.select(*keys).distinct(), index, plan, i, singles, bundles, fr.open, spec.split_case3)
        ext = ext.select(*[F.col(c).alias(f"k_{c}") for c in keys], "x", *[f"n{w}" for w in bundles])
        out = frontier.join(ext.hint("merge"), reduce(lambda a, b: a & b, [F.col(c) == F.col(f"k_{c}") for c in keys]))
    kept = [F.col(f"n{j}").alias(f"q{j}") if j in bundles else F.col(f"q{j}") for j in range(i) if j in bundles or j not in fr.open]
    out = _no_clash(out.select(*kept, F.col("x").alias(f"q{i}")), plan, i, set(touched), spec)
    for a, op, b in plan.query.cross:
        pa, pb = plan.order.index(a), plan.order.index(b)
        if max(pa, pb) == i:
            out = out.where(F.expr(f"q{pa} {op} q{pb}"))
    return Frontier(out, fr.open - set(bundles), grown)


#: Extensions are shared if there are at most this many keys for each row.
SHARES_BELOW = 0.5
#: A plan of more levels than this is cut by a table, so that its size and what a lost executor costs stay bounded.
LEVELS_A_PLAN = 8


def enumerate_packed(index: CandidateIndex, plan: MatchPlan, spec: MatchSpec, cand: list[DataFrame], roots: DataFrame | None = None) -> list[Frontier]:
    """All levels' frontiers; the last one holds the packed matches."""
    levels = [seed(cand[plan.order[0]] if roots is None else roots, plan, spec.bundle_most)]
    steps = 0
    for i in range(1, plan.query.n):
        steps += 1
        if steps > LEVELS_A_PLAN:
            levels[-1], steps = levels[-1].stored(f"level{i}"), 0
        levels.append(extend(levels[-1], index, plan, i, spec, cand[plan.order[i]]))
    return levels


def level_counters(levels: list[DataFrame], plan: MatchPlan) -> DataFrame:
    """level, rows, members (choices that the rows stand for, before conflicts), keys (distinct
    images of the next place's back-neighbours): what an extension costs with and without sharing."""
    out = None
    for i, df in enumerate(levels):
        size: Column = reduce(lambda a, b: a * b, [F.size(f"q{j}").cast("double") for j in range(i + 1) if plan.bundled[j]], F.lit(_ONE))
        keys = plan.back[i + 1] if i + 1 < len(levels) else ()
        key = F.count_distinct(F.struct(*[f"q{j}" for j in keys])) if keys else F.lit(0)
        row = df.agg(F.count("*").alias("rows"), F.coalesce(F.sum(size), F.lit(0.0)).cast("long").alias("members"), key.cast("long").alias("keys"))
        row = row.select(F.lit(i + 1).alias("level"), "rows", "members", "keys")
        out = row if out is None else out.unionByName(row)
    return out

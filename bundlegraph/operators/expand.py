"""From packed matches to flat ones, to some of their columns, or to their number."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import MatchPlan
from .index import CandidateIndex
from .levels import Frontier, arrays, placed

_WHOLE = "decimal(38,0)"


def _differ(df: DataFrame, plan: MatchPlan, i: int, others: list[int]) -> DataFrame:
    for j in others:
        if plan.clash(i, j):
            df = df.where(F.col(f"q{i}") != F.col(f"q{j}"))
    return df


def flat(fr: Frontier, index: CandidateIndex, plan: MatchPlan, semantics: str = "iso", skip: set[int] = frozenset()) -> DataFrame:
    """One row a match: bundles are exploded one by one, open ones by a join on pairs, and clashing
    choices leave at once. Places in `skip` stay as they are."""
    df, sets = fr.df, arrays(fr.df)
    done: list[int] = []
    for j in sorted(set(placed(df)) - sets):  # single images may still clash if conflicts were left for the end
        df = _differ(df, plan, j, done) if semantics != "hom" else df
        done.append(j)
    for j in sorted((sets | fr.open) - set(skip)):
        if j in fr.open:
            w = plan.back[j][0]
            near = index.pairs(w, j).select(F.col("va").alias("__v"), F.col("vb").alias(f"q{j}"))
            df = df.join(index.near(near, w, j), F.col(f"q{w}") == F.col("__v")).drop("__v")
        else:
            df = df.withColumn(f"q{j}", F.explode(f"q{j}"))
        df = _differ(df, plan, j, done) if semantics != "hom" else df
        done.append(j)
    return df


def named(matches: DataFrame, plan: MatchPlan) -> DataFrame:
    """Columns by query vertex name, in the query's order."""
    at = {u: i for i, u in enumerate(plan.order)}
    return matches.select(*[F.col(f"q{at[u]}").alias(plan.query.names[u]) for u in range(plan.query.n)])


def partitions(items: list[int]) -> list[list[list[int]]]:
    """All partitions of a small list into blocks."""
    if not items:
        return [[]]
    head, *rest = items
    out = []
    for p in partitions(rest):
        out.append([[head], *p])
        out += [[*p[:k], [head, *p[k]], *p[k + 1 :]] for k in range(len(p))]
    return out


def distinct_choices(bundles: list[int]) -> Column:
    """How many ways to choose different members, one of each bundle: Moebius sum over partitions."""

    def block(b: list[int]) -> tuple[int, Column]:
        sign = 1
        for k in range(1, len(b)):
            sign *= -k
        common = reduce(F.array_intersect, [F.col(f"q{j}") for j in b])
        return sign, F.size(common).cast(_WHOLE)

    terms = []
    for p in partitions(bundles):
        blocks = [block(b) for b in p]
        weight = reduce(lambda x, y: x * y, [s for s, _ in blocks])
        terms.append(reduce(lambda x, y: (x * y).cast(_WHOLE), [c for _, c in blocks]) * F.lit(weight))
    return reduce(lambda x, y: (x + y).cast(_WHOLE), terms)


def _clashes(plan: MatchPlan, semantics: str, j: int) -> set[int]:
    return set() if semantics == "hom" else {k for k in range(plan.query.n) if k != j and plan.clash(j, k)}


def with_counts(
    fr: Frontier, index: CandidateIndex, plan: MatchPlan, semantics: str = "iso", most: int = 4, name: str = "weight", keep: set[int] = frozenset(),
) -> DataFrame:
    """Adds the number of matches of each packed row, or of each row that is left after the bundles
    of `keep` are exploded.

    Open bundles that clash with nothing, or only with others that surely hold the same set, count by
    their length and are never made. Single images are taken out of the bundles that they clash with.
    Bundles that cannot clash multiply; groups of up to `most` clashing bundles use inclusion and
    exclusion; larger groups are exploded down to that size.
    """
    factors: list[Column] = []
    counted: set[int] = set()
    df = fr.df
    for j in sorted(fr.open - set(keep)):
        if j in counted:
            continue
        w = plan.back[j][0]
        twins = _clashes(plan, semantics, j) | {j}
        sign = index.signature(w, j)
        alike = len(twins) == 1 or (sign is not None and all(k in fr.open and k not in keep and index.signature(plan.back[k][0], k) == sign for k in twins))
        if alike and (len(twins) == 1 or all(_clashes(plan, semantics, k) | {k} == twins for k in twins)):
            d = f"__d{j}"
            near = index.degrees(w, j).select(F.col("va").alias("__v"), F.col("d").alias(d))
            df = df.join(index.near(near, w, j), F.col(f"q{w}") == F.col("__v")).drop("__v")
            factors += [F.greatest(F.col(d) - k, F.lit(0)).cast(_WHOLE) for k in range(len(twins))]
            counted |= twins
    df = _held(df, fr.open - counted, index, plan)
    sets = arrays(fr.df) | (fr.open - counted)
    done = sorted(set(placed(fr.df)) - sets)
    if semantics != "hom":
        for k, j in enumerate(done):
            df = _differ(df, plan, j, done[:k])
    for j in sorted(keep):
        if j in sets:
            df = df.withColumn(f"q{j}", F.explode(f"q{j}"))
            df = _differ(df, plan, j, done) if semantics != "hom" else df
            done.append(j)
    left = sorted(sets - set(keep))
    if semantics == "hom":
        factors += [F.size(f"q{j}").cast(_WHOLE) for j in left]
        return df.withColumn(name, _product(factors))
    groups: list[list[int]] = []
    for j in left:
        near = [g for g in groups if any(plan.clash(j, k) for k in g)]
        groups = [g for g in groups if g not in near] + [[j, *(k for g in near for k in g)]]
    for g in groups:
        while len(g) > most:
            j = g.pop()
            df = _differ(df.withColumn(f"q{j}", F.explode(f"q{j}")), plan, j, done)
            done.append(j)
    for g in groups:
        for j in g:
            for k in done:
                if plan.clash(j, k):
                    df = df.withColumn(f"q{j}", F.array_remove(f"q{j}", F.col(f"q{k}")))
    return df.withColumn(name, _product(factors + [distinct_choices(g) for g in groups]))


def _held(df: DataFrame, opened: frozenset[int], index: CandidateIndex, plan: MatchPlan) -> DataFrame:
    """Open bundles as arrays, beside whatever other columns there are."""
    for j in sorted(opened):
        w = plan.back[j][0]
        near = index.lists(w, j).select(F.col("va").alias("__v"), F.col("nbrs").alias(f"q{j}"))
        df = df.join(index.near(near, w, j), F.col(f"q{w}") == F.col("__v")).drop("__v")
    return df


def _product(factors: list[Column]) -> Column:
    return reduce(lambda x, y: (x * y).cast(_WHOLE), factors, F.lit(1).cast(_WHOLE))


def count(fr: Frontier, index: CandidateIndex, plan: MatchPlan, semantics: str = "iso") -> DataFrame:
    """One row, n: the number of matches, without flattening them."""
    return with_counts(fr, index, plan, semantics).agg(F.coalesce(F.sum("weight"), F.lit(0)).cast("long").alias("n"))


def counted(fr: Frontier, index: CandidateIndex, plan: MatchPlan, semantics: str, places: list[int]) -> DataFrame:
    """The images of some places and n, the matches that have them: bundles that are not asked for
    collapse to their number of choices."""
    rows = with_counts(fr, index, plan, semantics, keep=set(places))
    return rows.groupBy(*[f"q{j}" for j in places]).agg(F.sum("weight").cast("long").alias("n")).where("n > 0")


def distinct_images(fr: Frontier, index: CandidateIndex, plan: MatchPlan, semantics: str, places: list[int]) -> DataFrame:
    """The images of some places, each once. A bundle that is not asked for and clashes with nothing
    only has to be non-empty, so it is never exploded; the others need a valid choice."""
    idle = {j for j in arrays(fr.df) | fr.open if j not in places and not _clashes(plan, semantics, j)}
    df = flat(fr, index, plan, semantics, skip=idle)
    for j in sorted(idle & fr.open):
        w = plan.back[j][0]
        some = index.pairs(w, j).select(F.col("va").alias("__v"))
        df = df.join(index.near(some, w, j), F.col(f"q{w}") == F.col("__v"), "left_semi")
    return df.select(*[f"q{j}" for j in places]).distinct()


__all__ = ["count", "counted", "distinct_choices", "distinct_images", "flat", "named", "partitions", "with_counts"]

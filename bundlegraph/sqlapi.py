"""SQL surface: patterns as text, a table function over broadcast graphs, and set functions."""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import ArrayType, LongType

from .model import MatchSpec, PropertyGraph
from .operators.match import match
from .plans.pattern import parse


def match_sql(g: PropertyGraph, text: str, spec: MatchSpec = MatchSpec()) -> DataFrame:
    """Matches of a pattern such as (a:part)-(b:part)-(c:part); a < c RETURN ...

    Without RETURN all columns of each match; RETURN a, b: these columns of each match; RETURN
    DISTINCT a, b: each once; RETURN a, b, COUNT: each with its number of matches; RETURN COUNT: their
    number. Bundles that are not asked for are not exploded by the last three.
    """
    pattern, _, tail = re.split(r"\s(RETURN)\s", text, maxsplit=1) if re.search(r"\sRETURN\s", text) else (text, "", "")
    found = match(g, parse(pattern, directed=g.directed), spec)
    if not tail:
        return found.flat()
    distinct = tail.strip().upper().startswith("DISTINCT ")
    names = [n.strip() for n in (tail.strip()[9:] if distinct else tail).split(",")]
    wrong = [n for n in names if n not in found.plan.query.names and n.upper() != "COUNT"]
    if wrong:
        raise ValueError(f"not in the pattern: {wrong}")
    if names[-1].upper() == "COUNT":
        return found.count() if len(names) == 1 else found.count_by(*names[:-1])
    return found.select(*names, distinct=distinct)


@pandas_udf(ArrayType(LongType()))
def intersect_sorted(a: pd.Series, b: pd.Series) -> pd.Series:
    """Common members of two sorted arrays without repeats; null if either is null."""
    import numpy as np

    return pd.Series([None if x is None or y is None else np.intersect1d(x, y, assume_unique=True) for x, y in zip(a, b)])


@pandas_udf(ArrayType(LongType()))
def bundle_union(bundles: pd.Series) -> list:
    """Aggregate: the sorted union of a group's bundles; null bundles count as empty."""
    import numpy as np

    held = [x for x in bundles if x is not None]
    return np.unique(np.concatenate(held)).tolist() if held else []


def register(spark: SparkSession) -> None:
    """intersect_sorted(a, b), bundle_union(bundle) and expand_packed(pinned, bundle) for SQL."""
    spark.udf.register("intersect_sorted", intersect_sorted)
    spark.udf.register("bundle_union", bundle_union)
    spark.udtf.register("expand_packed", ExpandPacked)


@udtf(returnType="image bigint")
class ExpandPacked:
    """The members of a bundle that the pinned images leave free, one row each."""

    def eval(self, pinned: list, bundle: list):
        for x in bundle or ():
            if x not in (pinned or ()):
                yield (x,)


def register_graph(spark: SparkSession, name: str, g: PropertyGraph, most_arcs: int = 1_000_000) -> None:
    """subgraph_matches_<name>(pattern): rows (place string, image bigint, n bigint) of every match.

    A table function cannot start jobs, so the graph is collected once, up to a checked size.
    """
    arcs = g.edges.select("src", "dst", "elabel").distinct().limit(most_arcs + 1).collect()
    if len(arcs) > most_arcs:
        raise ValueError("the graph is too large for a table function; use match_sql")
    found = g.vertices.select("id", "label").limit(most_arcs + 1).collect()
    if len(found) > most_arcs:
        raise ValueError("the graph has too many vertices for a table function; use match_sql")
    labels = {r.id: r.label for r in found}
    held, directed = [(r.src, r.dst, r.elabel) for r in arcs], g.directed

    @udtf(returnType="n bigint, place string, image bigint")
    class Matches:
        def eval(self, pattern: str):
            from .operators.kernel import Search
            from .plans.analysis import make_plan

            q = parse(pattern, directed=directed)
            spec = MatchSpec(colouring="all_pinned", prune_dominated=False)
            cand = [frozenset(v for v, lab in labels.items() if q.labels[i] in (None, lab)) for i in range(q.n)]
            plan = make_plan(q, [len(c) for c in cand], spec)
            at = {u: i for i, u in enumerate(plan.order)}
            lists: dict = {}
            for (u, w), kinds in q.links().items():
                pairs = None
                for a, b, e in kinds:
                    one = {(s, d) if a == u else (d, s) for s, d, lab in held if e in (None, lab)}
                    pairs = one if pairs is None else pairs & one
                for x, y in pairs:
                    if x in cand[u] and y in cand[w]:
                        lists.setdefault((at[u], at[w]), {}).setdefault(x, set()).add(y)
                        lists.setdefault((at[w], at[u]), {}).setdefault(y, set()).add(x)
                lists.setdefault((at[u], at[w]), {}), lists.setdefault((at[w], at[u]), {})
            lists = {k: {v: frozenset(s) for v, s in d.items()} for k, d in lists.items()}
            rows: list = []
            Search(plan, lists, [cand[u] for u in plan.order], spec).roots(sorted(cand[plan.order[0]]), lambda im: rows.append(list(im)))
            for n, image in enumerate(rows):
                for i, u in enumerate(plan.order):
                    yield n, q.names[u], image[i]

    spark.udtf.register(f"subgraph_matches_{name}", Matches)


def with_intersection(df: DataFrame, a: str, b: str, name: str, vectorised: bool = False) -> DataFrame:
    """Intersection by the built-in function (default; stays in the JVM) or by numpy."""
    return df.withColumn(name, intersect_sorted(a, b) if vectorised else F.array_sort(F.array_intersect(a, b)))

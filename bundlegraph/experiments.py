"""The experiment workloads: methods against query sets, sweeps and ablations, as tables of runs.

`python -m bundlegraph.experiments SF_DIR [OUT.json]` runs them at small counts and prints the reports.
"""

from __future__ import annotations

import json
import sys
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import metrics
from .model import MatchSpec, PropertyGraph, QueryGraph
from .operators import baselines
from .operators.batched import batched
from .operators.kernel import kernel_counters
from .operators.match import match, prepare
from .workload import SOCIAL, random_walk_queries, social

FULL = MatchSpec()
#: A run: (graph, query) to (milliseconds of preparation, one-row count).
Run = Callable[[PropertyGraph, QueryGraph], tuple[float, DataFrame]]


def by_spec(spec: MatchSpec, flat: bool = False) -> Run:
    def run(g: PropertyGraph, q: QueryGraph) -> tuple[float, DataFrame]:
        r = match(g, q, spec)
        return r.metrics["pre_ms"], r.flat().agg(F.count("*").alias("n")) if flat else r.count()

    return run


def by_result(f: Callable) -> Run:
    """A baseline that gives a MatchResult: it writes its matches out, so they are flattened."""

    def run(g: PropertyGraph, q: QueryGraph) -> tuple[float, DataFrame]:
        r = f(g, q)
        return r.metrics["pre_ms"], r.flat().agg(F.count("*").alias("n"))

    return run


def by_clock(f: Callable) -> Run:
    """A baseline that searches while it is called and tells how long its preparation took."""

    def run(g: PropertyGraph, q: QueryGraph) -> tuple[float, DataFrame]:
        clock: dict = {}
        df = f(g, q, clock=clock)
        return clock["pre_ms"], df.agg(F.count("*").alias("n"))

    return run


METHODS: dict[str, Run] = {
    "full": by_spec(FULL),
    "kernel": by_spec(FULL.but(engine="kernel")),
    "b1_dynamic_failing_set": by_clock(baselines.dynamic_failing_set),
    "b2_static_leaf_grouping": by_result(baselines.static_leaf_grouping),
    "b3_dynamic_equivalence": by_clock(baselines.dynamic_equivalence),
    "b4_guarded": by_clock(baselines.guarded),
    "b5_neighbour_classes": by_clock(baselines.neighbour_classes),
    "b6_batch_homomorphism": by_result(baselines.batch_homomorphism),
    "b7_backtracking": by_result(baselines.backtracking),
    "b8_levels": by_result(baselines.level_by_level),
    "b9_vertex_cover": by_result(baselines.vertex_cover),
    "b10_sql_join": lambda g, q: (0.0, baselines.sql_join(g, q).agg(F.count("*").alias("n"))),
}
COLOURS = {c: by_spec(FULL.but(colouring=c)) for c in ("risk", "risk_smoothed", "all_pinned", "all_bundled", "tail_only", "vertex_cover")}
REUSE = {"reuse": by_spec(FULL), "reuse_dep": by_spec(FULL.but(reuse="dep")), "no_reuse": by_spec(FULL.but(reuse=None))}
PRUNING_SPECS = {
    "both": FULL.but(engine="kernel"), "no_dominated": FULL.but(engine="kernel", prune_dominated=False),
    "no_failing": FULL.but(engine="kernel", prune_failing=False), "neither": FULL.but(engine="kernel", prune_dominated=False, prune_failing=False),
}
PRUNING = {name: by_spec(spec) for name, spec in PRUNING_SPECS.items()}
ORDERS = {o: by_spec(FULL.but(order=o)) for o in ("candidate_ratio", "dense_first", "guard_first", "structure_first", "smallest_candidates")}


def run_all(g: PropertyGraph, queries: dict[str, QueryGraph], methods: dict[str, Run], cap_s: float | None = None, repeats: int = 3, warm_up: int = 1) -> DataFrame:
    """Rows of metrics.RUNS for each method, query and repeat. Warm-up runs are not recorded. Raises
    if two methods that ended in time found different numbers of matches."""
    spark, g, out = g.edges.sparkSession, g.store(), []
    for name, q in queries.items():
        for m, f in methods.items():
            for k in range(-warm_up, repeats):
                row = metrics.timed(spark, m, name, q.n, lambda: f(g, q), cap_s, k)  # noqa: B023
                if k >= 0:
                    out.append(row)
    runs = spark.createDataFrame(out, metrics.RUNS)
    found: dict[str, set] = {}
    for row in out:
        if not row[7]:
            found.setdefault(row[1], set()).add(row[8])
    wrong = {q: ns for q, ns in found.items() if len(ns) > 1}
    if wrong:
        raise AssertionError(f"methods disagree on the number of matches: {wrong}")
    return runs


def query_set(g: PropertyGraph, sizes: tuple[int, ...] = (4, 8, 16, 24, 32), count: int = 2, seed: int = 1) -> dict[str, QueryGraph]:
    """Random-walk queries by size; sizes over 4 are dealt into sparse and dense halves."""
    out, held = {}, {}
    for size in sizes:
        for density in ("any",) if size <= 4 else ("sparse", "dense"):
            for k, q in enumerate(random_walk_queries(g, size, density, count, seed + size, held=held)):
                out[f"n{size}-{density}-{k}"] = q
    return out


def limit_sweep(g: PropertyGraph, q: QueryGraph, limits: tuple[int, ...] = (1_000, 10_000, 100_000, 1_000_000), specs: dict[str, MatchSpec] | None = None) -> DataFrame:
    """method, lim, n, ms: time to the first `lim` matches, by root batches."""
    spark, g, out = g.edges.sparkSession, g.store(), []
    for name, spec in (specs or {"full": FULL, "tail_only": FULL.but(colouring="tail_only"), "all_pinned": FULL.but(colouring="all_pinned")}).items():
        for lim in limits:
            found, facts = batched(g, q, spec.but(limit=lim))
            out.append((name, lim, facts["rows"], facts["ms"]))
    return spark.createDataFrame(out, "method string, lim long, n long, ms double")


def counters(g: PropertyGraph, queries: dict[str, QueryGraph], specs: dict[str, MatchSpec]) -> DataFrame:
    """method, query, level, rows, members, keys: the deterministic side of the ablations."""
    g, out = g.store(), None
    for name, q in queries.items():
        for m, spec in specs.items():
            part = match(g, q, spec).counters().withColumns({"method": F.lit(m), "query": F.lit(name)})
            out = part if out is None else out.unionByName(part)
    return out


def search_work(g: PropertyGraph, queries: dict[str, QueryGraph], specs: dict[str, MatchSpec]) -> DataFrame:
    """method, query, name, n: the depth-first search's counters under each setting."""
    g, out = g.store(), None
    for name, q in queries.items():
        for m, spec in specs.items():
            plan, cand, index = prepare(g, q, spec)
            part = kernel_counters(index, plan, spec, cand).withColumns({"method": F.lit(m), "query": F.lit(name)})
            out = part if out is None else out.unionByName(part)
    return out


def nine_shapes(g: PropertyGraph, cap_s: float | None = None, repeats: int = 1, warm_up: int = 0) -> DataFrame:
    """The nine directed shapes under the method, its flat variant and the plain multiway join."""
    methods = {"full": by_spec(FULL), "all_pinned": by_spec(FULL.but(colouring="all_pinned")), "sql_join": METHODS["b10_sql_join"]}
    return run_all(g, {n: social(n) for n in SOCIAL}, methods, cap_s, repeats, warm_up)


def main(sf_dir: str, out: str | None = None, count: int = 1, cap_s: float = 20.0) -> dict:
    from .sources import graphs as G

    spark = SparkSession.builder.getOrCreate()
    g = G.remembered(spark, sf_dir, "copart-brands", ("lineitem", "part"), lambda: G.copart(spark, sf_dir, 1, "concat(p_type, ' ', p_brand)"))
    report, began = {"sf": sf_dir.rstrip("/").split("/")[-1]}, time.time()
    plain = lambda df: [{k: round(v, 3) if isinstance(v, float) else v for k, v in r.asDict().items()} for r in df.collect()]
    sets = query_set(g, count=count)
    report["queries"] = {k: [q.n, len(q.edges)] for k, q in sets.items()}
    keys = ("full", "b1_dynamic_failing_set", "b2_static_leaf_grouping", "b4_guarded", "b6_batch_homomorphism", "b10_sql_join")
    runs = run_all(g, sets, {k: METHODS[k] for k in keys}, cap_s, repeats=1, warm_up=0).cache()
    report["methods"], report["by_size"] = plain(metrics.summary(runs).orderBy("mean_total_ms")), plain(metrics.by_size(runs).orderBy("method", "size"))
    report["against_second_best"] = plain(metrics.against_second_best(runs, "full").orderBy("query"))
    report["scatter"] = {k: plain(metrics.scatter(runs, "full", k)) for k in keys[1:]}
    small = {k: q for k, q in sets.items() if q.n <= 8}
    for name, methods in (("colouring", {k: COLOURS[k] for k in ("risk", "all_pinned", "all_bundled", "tail_only")}), ("reuse", REUSE), ("orders", ORDERS)):
        report[name] = plain(metrics.summary(run_all(g, small, methods, cap_s, repeats=1, warm_up=1)).select("method", "mean_enum_ms", "mean_total_ms", "unsolved").orderBy("mean_total_ms"))
    report["pruning_work"] = plain(search_work(g, small, PRUNING_SPECS).groupBy("method", "name").agg(F.sum("n").alias("n")).where("name IN ('nodes', 'computed')").orderBy("name", "method"))
    report["seconds"] = round(time.time() - began, 1)
    text = json.dumps(report, indent=1)
    if out:
        with open(out, "w") as f:
            f.write(text)
    print(text)
    return report


if __name__ == "__main__":
    main(*sys.argv[1:3])

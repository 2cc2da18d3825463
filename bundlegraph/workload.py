"""Query sets: the nine directed, labelled shapes, a pattern set, and seeded random walks."""

from __future__ import annotations

import random

from pyspark.sql import functions as F

from .model import PropertyGraph, QueryGraph
from .plans.pattern import parse

#: Nine own shapes on the trade graph (directed, both kinds of labels).
SOCIAL = {
    "s1": "(r:region)<-[:IN_REGION]-(n:nation)<-[:LIVES_IN]-(c:customer)-[:PLACED]->(o:orders)-[:CONTAINS]->(p:part)<-[:SUPPLIES]-(s:supplier)-[:BASED_IN]->(m:nation)",
    "s2": "(c:customer)-[:PLACED]->(o:orders)-[:SHIPPED_BY]->(s:supplier)-[:BASED_IN]->(n:nation), (c)-[:LIVES_IN]->(n)",
    "s3": "(o:orders)-[:CONTAINS]->(p:part)<-[:SUPPLIES]-(s:supplier)-[:SUPPLIES]->(x:part), (o)-[:CONTAINS]->(x)",
    "s4": "(c:customer)-[:PLACED]->(o:orders)-[:CONTAINS]->(p:part), (o)-[:CONTAINS]->(x:part), (o)-[:SHIPPED_BY]->(s:supplier)",
    "s5": "(p:part)<-[:CONTAINS]-(o:orders)<-[:PLACED]-(c:customer)-[:PLACED]->(y:orders)-[:CONTAINS]->(x:part)",
    "s6": "(n:nation)<-[:LIVES_IN]-(c:customer)-[:PLACED]->(o:orders)-[:CONTAINS]->(p:part)<-[:CONTAINS]-(y:orders)<-[:PLACED]-(d:customer)",
    "s7": "(c:customer)-[:PLACED]->(o:orders)-[:CONTAINS]->(p:part), (o)-[:CONTAINS]->(x:part), (o)-[:SHIPPED_BY]->(s:supplier), (s)-[:SUPPLIES]->(p)",
    "s8": "(p:part)<-[:CONTAINS]-(o:orders)<-[:PLACED]-(c:customer)-[:PLACED]->(y:orders)-[:CONTAINS]->(x:part), (o)-[:SHIPPED_BY]->(s:supplier), (y)-[:SHIPPED_BY]->(s)",
    "s9": "(n:nation)<-[:LIVES_IN]-(c:customer)-[:PLACED]->(o:orders)-[:CONTAINS]->(p:part)<-[:CONTAINS]-(y:orders)<-[:PLACED]-(d:customer), (d)-[:LIVES_IN]->(n)",
}


def social(name: str) -> QueryGraph:
    return parse(SOCIAL[name], directed=True)


#: Undirected shapes; L stands for a label of one's own.
SHAPES = {
    "edge": "(a)-(b)",
    "path3": "(a)-(b)-(c)",
    "triangle": "(a)-(b)-(c)-(a)",
    "path4": "(a)-(b)-(c)-(d)",
    "cycle4": "(a)-(b)-(c)-(d)-(a)",
    "cycle5": "(a)-(b)-(c)-(d)-(e)-(a)",
    "star3": "(a)-(b), (a)-(c), (a)-(d)",
    "diamond": "(a)-(b)-(c)-(d)-(a)-(c)",
    "tailed_triangle": "(a)-(b)-(c)-(a)-(d)",
    "clique4": "(a)-(b)-(c)-(d)-(a)-(c), (b)-(d)",
    "house": "(a)-(b)-(c)-(d)-(a), (a)-(e)-(b)",
    "bow_tie": "(a)-(b)-(c)-(a)-(d)-(e)-(a)",
    "tree": "(a)-(b), (a)-(c), (b)-(d), (b)-(e), (c)-(f)",
}


def shape(name: str, labels: dict[str, str] | None = None, where: str | None = None) -> QueryGraph:
    """A shape with labels of some vertices, and one predicate on every vertex."""
    q = parse(SHAPES[name], directed=False)
    tests = (where,) * q.n if where else q.where
    return QueryGraph(q.names, tuple((labels or {}).get(n) for n in q.names), q.edges, False, tests, q.cross)


def random_walk_queries(g: PropertyGraph, size: int, density: str, count: int, seed: int, tries: int = 400, held: dict | None = None) -> list[QueryGraph]:
    """Induced subgraphs on vertices met by a walk from seeded roots; each has a match by construction.

    density: sparse (average degree below 3), dense (3 or more) or any. `held` keeps the walks of a graph
    for further calls: sparse and dense queries are picked from the same ones.
    """
    tries = min(tries, 8 * count if density == "any" else 24 * count)
    key, held = (size, count, seed, tries), {} if held is None else held
    if key not in held:
        held[key] = _walked(g, *key)
    full, inside, labels = held[key]
    out: list[QueryGraph] = []
    for w in full:
        at = {v: i for i, v in enumerate(w)}
        edges = sorted({tuple(sorted((at[a], at[b]))) for a, b in inside if a in at and b in at})
        degree = 2 * len(edges) / size
        q = QueryGraph(tuple(f"u{i}" for i in range(size)), tuple(labels[v] for v in w), tuple((a, b, None) for a, b in edges))
        if (density == "any" or (density == "sparse") == (degree < 3)) and len(q.components()) == 1 and q not in out:
            out.append(q)
        if len(out) == count:
            break
    return out


def _walked(g: PropertyGraph, size: int, count: int, seed: int, tries: int) -> tuple[list[list[int]], set[tuple[int, int]], dict[int, str | None]]:
    """Vertex sets of the walks that met `size` vertices, the arcs among all of these and their labels.

    All walks take a step in one job: a walk goes to the neighbour of smallest seeded hash, out of all
    that its vertex has, so only one vertex for each walk comes to the driver. An arc that is there twice
    changes no step, so the arcs are only scanned.
    """
    rng = random.Random(seed)
    spark = g.edges.sparkSession
    arcs = g.edges.select("src", "dst").where("src <> dst")
    pool = [r.src for r in arcs.select("src").distinct().orderBy(F.xxhash64("src", F.lit(seed))).limit(max(4 * count, 64)).collect()]
    walks = [[rng.choice(pool)] for _ in range(tries)] if pool else []
    for step in range(6 * size):
        now = [(k, w[-1]) for k, w in enumerate(walks) if len(set(w)) < size]
        if not now:
            break
        at = F.broadcast(spark.createDataFrame(now, "walk int, at long"))  # one row a walk
        drawn = F.min_by("dst", F.xxhash64("dst", "walk", F.lit(seed), F.lit(step)))
        for r in arcs.join(at, F.col("src") == F.col("at")).groupBy("walk").agg(drawn.alias("to")).collect():
            walks[r.walk].append(r.to)
    full = [sorted(set(w)) for w in walks if len(set(w)) == size]
    every = sorted({v for w in full for v in w})
    if not every:
        return [], set(), {}
    inside = {(r.src, r.dst) for r in arcs.where(F.col("src").isin(every) & F.col("dst").isin(every)).collect()}
    labels = {r.id: r.label for r in g.vertices.where(F.col("id").isin(every)).select("id", "label").collect()}
    return full, inside, labels

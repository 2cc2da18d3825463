"""Depth-first search of packed matches inside a task, over a broadcast index of checked size.

The search keeps one image (or set of images) for each placed query vertex on a stack, reuses
extension sets while what they depend on stands still, and skips siblings when a failure does not
blame the vertex at hand. Sets of places are bit masks. It holds one path and one cache entry for
each place, whatever the number of matches; rows leave in batches.
"""

from __future__ import annotations

import time
from collections import Counter
from collections.abc import Iterable, Iterator
from math import prod

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..model import MatchPlan, MatchSpec
from ..plans.analysis import closed

Lists = dict[tuple[int, int], dict[int, frozenset[int]]]
_NONE: frozenset[int] = frozenset()


class Stop(Exception):
    """The limit or the deadline is reached."""


class Search:
    """One search over one index. `lists[i, j][v]`: candidates of place j next to v, a candidate of i."""

    def __init__(self, plan: MatchPlan, lists: Lists, cand: list[frozenset[int]], spec: MatchSpec, deadline: float | None = None):
        self.plan, self.lists, self.cand, self.spec, self.deadline = plan, lists, cand, spec, deadline
        n = self.n = plan.query.n
        self.iso = spec.semantics != "hom"
        self.count: Counter = Counter()
        mask = lambda places: sum(1 << p for p in places)
        self.dep = [[mask(closed({w}, i, plan.back, plan.bundled)) for i in range(n + 1)] for w in range(n)]
        self.short = [0] * n
        for i in range(n):
            for w in plan.back[i]:
                self.short[i] |= self.dep[w][i]
        self.all = (1 << n) - 1
        self.before = [[j for j in range(i) if plan.clash(i, j)] for i in range(n)]
        self.pinned_back = [plan.back_pinned(i) for i in range(n)]
        self.bundled_back = [plan.back_bundled(i) for i in range(n)]
        self.cached: list = [None] * n
        self.children = [[k for k in range(n) if plan.reusable[k] and plan.anchor[k] == i] for i in range(n)]
        self.tests = [[(plan.order.index(a), op, plan.order.index(b)) for a, op, b in plan.query.cross if max(plan.order.index(a), plan.order.index(b)) == i] for i in range(n)]
        self.found = 0

    # images are frozensets for bundled places and ints for pinned ones

    def reach(self, i: int, image: list) -> frozenset[int]:
        """The extension set R; empty if there is none."""
        self.count["computed"] += 1
        pinned, lists = self.pinned_back[i], self.lists
        if pinned:
            sets = sorted((lists[w, i].get(image[w], _NONE) for w in pinned), key=len)
            out = sets[0]
            for s in sets[1:]:
                out = out & s
            self.count["intersections"] += len(sets) - 1
            self.count["scanned"] += len(sets[0])
            return out
        w = min(self.bundled_back[i], key=lambda k: len(image[k]))
        self.count["scanned"] += sum(len(lists[w, i].get(x, _NONE)) for x in image[w])
        return frozenset().union(*(lists[w, i].get(x, _NONE) for x in image[w]))

    def entries(self, i: int, image: list) -> list[tuple]:
        """(image of place i, {place: new bundle}) for each child, complete before any is tried.

        Conflicts with other places are no part of it, so it can be replayed elsewhere.
        """
        if not self.plan.back[i]:
            every = self.cand[i]
            return [(every, {})] if self.plan.bundled[i] and every else [] if self.plan.bundled[i] else [(v, {}) for v in sorted(every)]
        r = self.reach(i, image)
        if len(r) < self.plan.need[i] or not r:
            self.count["pruned_dominated"] += bool(r)
            return []
        bundles, mine = self.bundled_back[i], self.plan.bundled[i]
        if not bundles:
            return [(r, {})] if mine else [(v, {}) for v in sorted(r)]
        if mine and prod(len(image[w]) for w in bundles) < len(r):
            self.count["case4_split"] += 1
            out = []
            base = [self.lists[w, i].get(image[w], _NONE) for w in self.pinned_back[i]]
            stack = [({}, r if base else None, 0)]
            while stack:
                chosen, common, k = stack.pop()
                if k == len(bundles):
                    out.append((common, chosen))
                    continue
                w = bundles[k]
                for x in sorted(image[w], reverse=True):
                    near = self.lists[w, i].get(x, _NONE)
                    left = near if common is None else common & near
                    if left:
                        stack.append((chosen | {w: frozenset((x,))}, left, k + 1))
            return out
        self.count["case4_keep" if mine else "case3"] += 1
        out = []
        for v in sorted(r):
            cut = {w: image[w] & self.lists[i, w].get(v, _NONE) for w in bundles}
            if all(cut.values()):
                out.append((frozenset((v,)) if mine else v, cut))
        return out

    def clash(self, i: int, image: list) -> int | None:
        """A place whose single image is also the single image of place i."""
        v = image[i]
        if self.plan.bundled[i]:
            if len(v) > 1:
                return None
            (v,) = v
        for j in self.before[i]:
            x = image[j]
            if x == v or (self.plan.bundled[j] and len(x) == 1 and v in x):
                return j
        return None

    def some_choice(self, image: list) -> bool:
        """Is there an injective choice from the bundles?"""
        sets = [(i, x if self.plan.bundled[i] else (x,)) for i, x in enumerate(image)]
        sets.sort(key=lambda s: len(s[1]))

        def place(k: int, used: list[tuple[int, int]]) -> bool:
            if k == len(sets):
                return True
            i, xs = sets[k]
            for x in xs:
                if all(x != y or not self.plan.clash(i, j) for j, y in used) and place(k + 1, [*used, (i, x)]):
                    return True
            return False

        return place(0, [])

    def run(self, i: int, image: list, emit) -> int:
        """Searches below place i. Returns 0 if a match was found, else a closed failing set."""
        self.count["nodes"] += 1
        if self.deadline is not None and self.count["nodes"] % 512 == 0 and time.time() > self.deadline:
            raise Stop
        if i == self.n:
            if self.iso and not self.some_choice(image):
                self.count["no_choice"] += 1
                return self.all
            emit(image)
            return 0
        reuse = self.spec.reuse and self.plan.reusable[i]
        entry = self.cached[i] if reuse else None
        if entry is None:
            entry = self.entries(i, image)
            if reuse:
                self.cached[i] = entry
                self.count["cache_miss"] += 1
        else:
            self.count["cache_hit"] += 1
        if not entry:
            return self.short[i] or self.all
        own, blame, complete = 1 << i, self.short[i] | self.dep[i][i + 1], False
        for x, changed in entry:
            for k in self.children[i]:
                self.cached[k] = None
            old = [(w, image[w]) for w in changed]
            for w, b in changed.items():
                image[w] = b
            image.append(x)
            j = self.clash(i, image) if self.iso else None
            if j is not None:
                self.count["conflicts"] += 1
                fail = self.dep[i][i + 1] | self.dep[j][i + 1]
            elif not all(_compare(image[a], op, image[b]) for a, op, b in self.tests[i]):
                fail = self.all
            else:
                fail = self.run(i + 1, image, emit)
            image.pop()
            for w, b in old:
                image[w] = b
            if fail == 0:
                complete = True
            elif self.spec.prune_failing and not fail & own and not complete:
                self.count["pruned_failing"] += 1
                return fail
            else:
                blame |= fail
        for k in self.children[i]:
            self.cached[k] = None
        return 0 if complete else blame

    def roots(self, images: Iterable, emit) -> None:
        for v in images:
            self.cached = [None] * self.n
            self.run(1, [v], emit) if self.n > 1 else emit([v])


def _compare(a: int, op: str, b: int) -> bool:
    return {"<": a < b, ">": a > b, "<=": a <= b, ">=": a >= b, "<>": a != b}[op]


class DynamicSearch:
    """Flat depth-first search that picks the next query vertex for each partial match anew.

    Stand-in for the baselines with dynamic orders: the unplaced vertex next to the prefix with
    the smallest extension set goes first. Options: failing sets; classes of candidates that have
    equal index rows everywhere, of which one is searched and the others get its matches by exchange.
    """

    def __init__(self, plan: MatchPlan, lists: Lists, cand: list[frozenset[int]], spec: MatchSpec, failing: bool, classes: bool):
        self.plan, self.lists, self.cand, self.iso = plan, lists, cand, spec.semantics != "hom"
        self.failing, self.count, n = failing, Counter(), plan.query.n
        self.n, self.near = n, [sorted({j for j in range(n) if j in plan.back[i] or i in plan.back[j]}) for i in range(n)]
        self.twin: dict[int, int] = {}
        if classes:
            rows: dict[int, list] = {}
            for i in range(n):
                for v in cand[i]:
                    rows.setdefault(v, []).append((i, *(tuple(sorted(lists[i, j].get(v, _NONE))) for j in self.near[i])))
            seen: dict[tuple, int] = {}
            self.twin = {v: seen.setdefault(tuple(r), v) for v, r in sorted(rows.items())}

    def reach(self, u: int, image: dict[int, int]) -> frozenset[int]:
        self.count["computed"] += 1
        sets = sorted((self.lists[w, u].get(image[w], _NONE) for w in self.near[u] if w in image), key=len)
        out = sets[0]
        for s in sets[1:]:
            out = out & s
        return out

    def run(self, image: dict[int, int], why: dict[int, int]) -> tuple[list[dict[int, int]], int]:
        """Matches below, and if there are none a failing set (mask of places)."""
        self.count["nodes"] += 1
        if len(image) == self.n:
            return [dict(image)], 0
        edge = [u for u in range(self.n) if u not in image and any(w in image for w in self.near[u])]
        reach = {u: self.reach(u, image) for u in edge} if edge else {}
        u = min(edge, key=lambda k: (len(reach[k]), k)) if edge else min(k for k in range(self.n) if k not in image)
        options = reach[u] if edge else self.cand[u]
        because = 0
        for w in self.near[u]:
            if w in image:
                because |= why[w]
        out, blame = [], because
        done: dict[int, list[dict[int, int]]] = {}
        for v in sorted(options):
            taken = next((w for w, x in image.items() if x == v and self.plan.clash(u, w)), None) if self.iso else None
            if taken is not None:
                blame |= because | 1 << u | why[taken]
                continue
            like = self.twin.get(v, v)
            if self.iso and like in done and v not in image.values():
                swap = {done[like][0]: v, v: done[like][0]}
                got = [{k: swap.get(x, x) for k, x in m.items()} for m in done[like][1]]
                self.count["from_class"] += 1
                out += got
                continue
            got, fail = self.run(image | {u: v}, why | {u: because | 1 << u})
            if self.twin and like not in done:
                done[like] = (v, got)
            out += got
            if not got and self.failing and not out and not fail >> u & 1:
                self.count["pruned_failing"] += 1
                return [], fail
            blame |= fail
        return out, 0 if out else blame


def driver_lists(index, most: int) -> Lists | None:
    """The index as dictionaries, or None if it has more than `most` pairs (24 bytes each when collected)."""
    total = index.total()
    if total is None or total > most:
        return None
    links = index.links()
    out: Lists = {k: {} for i, j in links for k in ((i, j), (j, i))}
    if not links:
        return out
    found = index.links_table().toArrow()
    for b in found.to_batches(max_chunksize=100_000):
        for link, va, vb in zip(*(c.to_pylist() for c in b.columns)):
            i, j = divmod(link, 64)
            out[i, j].setdefault(va, []).append(vb)
            out[j, i].setdefault(vb, []).append(va)
    return {k: {v: frozenset(x) for v, x in d.items()} for k, d in out.items()}


def search_tasks(spark) -> int:
    """Searches are dealt finely over what the cluster has, so uneven roots even out."""
    return 4 * spark.sparkContext.defaultParallelism


def packed_schema(plan: MatchPlan) -> T.StructType:
    return T.StructType([T.StructField(f"q{i}", T.ArrayType(T.LongType()) if plan.bundled[i] else T.LongType()) for i in range(plan.query.n)])


def kernel_packed(index, plan: MatchPlan, spec: MatchSpec, cand: list[DataFrame], counters: bool = False) -> DataFrame | None:
    """Packed matches (or counters) of the kernel; None if the index is too large to be broadcast.

    Roots are dealt over the tasks; each task searches its own with the whole index.
    """
    lists = driver_lists(index, spec.kernel_arcs)
    if lists is None:
        return None
    spark = index.spark
    loose = [i for i in range(1, plan.query.n) if not plan.back[i]]
    sets = [frozenset(r.id for r in cand[plan.order[i]].limit(spec.kernel_arcs + 1).collect()) if i in loose else _NONE for i in range(plan.query.n)]
    if any(len(s) > spec.kernel_arcs for s in sets):
        return None
    shared = spark.sparkContext.broadcast((plan, lists, sets, spec))
    schema = packed_schema(plan)
    kinds = [pa.list_(pa.int64()) if b else pa.int64() for b in plan.bundled]

    def search(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        plan, lists, sets, spec = shared.value
        deadline = time.time() + spec.timeout_s if spec.timeout_s else None
        s = Search(plan, lists, sets, spec, deadline)
        rows: list[list] = []
        emit = lambda image: rows.append([sorted(x) if b else x for x, b in zip(image, plan.bundled)])

        def out():
            cols = list(zip(*rows)) if rows else [[]] * plan.query.n
            b = pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], schema.names)
            rows.clear()
            return b

        try:
            for b in batches:
                ids = b.column(0).to_pylist()
                for v in [frozenset(ids)] if plan.bundled[0] and ids else ids:
                    s.roots([v], emit)
                    if len(rows) >= 65_536 and not counters:
                        yield out()
                    if spec.limit is not None and s.count["nodes"] and len(rows) >= spec.limit and not counters:
                        raise Stop
        except Stop:
            pass
        if counters:
            yield pa.RecordBatch.from_pydict({"name": pa.array(list(s.count), pa.string()), "n": pa.array(list(s.count.values()), pa.int64())})
        else:
            yield out()

    # a limit counts rows of one task, a bundled root is one bundle: both search in one task
    alone = spec.limit is not None or plan.bundled[0]
    roots = cand[plan.order[0]].select("id").repartition(1 if alone else search_tasks(spark), "id")
    return roots.mapInArrow(search, "name string, n long" if counters else schema)


def regions(index, plan: MatchPlan, cand: list[DataFrame]) -> DataFrame:
    """root, link, va, vb: the part of the index that each root of a connected query can reach.

    Nothing is broadcast: one join for each link builds the regions.
    """
    from ..functions.scratch import written

    reach = {0: cand[plan.order[0]].select(F.col("id").alias("root"), F.col("id").alias("v"))}
    parts = None
    for i in range(1, plan.query.n):
        if not plan.back[i]:
            raise ValueError("regions need a connected query")
        grown = None
        for w in plan.back[i]:
            near = index.pairs(w, i).select(F.col("va").alias("x"), F.col("vb").alias("y"))
            one = reach[w].join(index.near(near, w, i), F.col("v") == F.col("x")).select("root", F.col("x").alias("va"), F.col("y").alias("vb"))
            part = one.select("root", F.lit(w * 64 + i).alias("link"), "va", "vb")
            parts = part if parts is None else parts.unionByName(part)
            seen = one.select("root", F.col("vb").alias("v")).distinct()
            # an image of place i must be reached from every placed neighbour
            grown = seen if grown is None else grown.join(seen.hint("merge"), ["root", "v"], "left_semi")
        reach[i] = written(grown, f"reach{i}") if i < plan.query.n - 1 else grown
    return parts


def search_regions(index, plan: MatchPlan, cand: list[DataFrame], schema, run) -> DataFrame:
    """run(root, lists) -> rows, once for each root with its region's lists."""
    import pandas as pd

    names = [f.name for f in schema.fields]

    def search(region: pd.DataFrame) -> pd.DataFrame:
        lists: dict = {k: {} for i in range(plan.query.n) for w in plan.back[i] for k in ((w, i), (i, w))}
        for link, va, vb in zip(region["link"].tolist(), region["va"].tolist(), region["vb"].tolist()):
            a, b = divmod(link, 64)
            lists[a, b].setdefault(va, set()).add(vb)
            lists[b, a].setdefault(vb, set()).add(va)
        rows = run(int(region["root"].iloc[0]), {k: {v: frozenset(x) for v, x in d.items()} for k, d in lists.items()})
        return pd.DataFrame(rows, columns=names)

    return regions(index, plan, cand).groupBy("root").applyInPandas(search, schema)


def region_packed(index, plan: MatchPlan, spec: MatchSpec, cand: list[DataFrame]) -> DataFrame:
    """Packed matches of a connected query, each root with its region; a task holds one region.

    A limit bounds the matches of each root and of the whole; a deadline ends the search of a root.
    """
    if plan.bundled[0]:
        raise ValueError("a region belongs to one root: place 0 must be pinned")
    if plan.query.n == 1:
        return cand[plan.order[0]].select(F.col("id").alias("q0"))

    def run(root: int, lists: Lists) -> list[list]:
        rows: list[list] = []
        deadline = time.time() + spec.timeout_s if spec.timeout_s else None

        def emit(image: list) -> None:
            rows.append([sorted(x) if b else x for x, b in zip(image, plan.bundled)])
            if spec.limit is not None and len(rows) >= spec.limit:
                raise Stop

        try:
            Search(plan, lists, [_NONE] * plan.query.n, spec, deadline).roots([root], emit)
        except Stop:
            pass
        return rows

    found = search_regions(index, plan, cand, packed_schema(plan), run)
    return found if spec.limit is None else found.limit(spec.limit)


#: Rows of regions that a task should hold when it counts the work of many roots.
REGION_ROWS = 500_000


def region_counters(index, plan: MatchPlan, spec: MatchSpec, cand: list[DataFrame]) -> DataFrame:
    """name, n: what `kernel_packed` would count, each root with its region; a task takes many roots.

    A root's work only depends on what it can reach, so the counters are those of the whole index.
    """
    if plan.bundled[0] or len(plan.query.components()) > 1:
        raise ValueError("the index is too large for the kernel, and regions need a connected query with place 0 pinned")
    import pandas as pd

    reach = [float(plan.counts[plan.order[0]])]
    total = reach[0]
    for i in range(1, plan.query.n):
        near = [reach[w] * index.mean(w, i) for w in plan.back[i]]
        reach.append(min(near))
        total += sum(near)
    groups = max(search_tasks(index.spark), int(min(total, 1e12)) // REGION_ROWS + 1)
    links = [k for i in range(plan.query.n) for w in plan.back[i] for k in ((w, i), (i, w))]

    def search(rows: pd.DataFrame) -> pd.DataFrame:
        rows, count = rows.sort_values("root"), Counter()
        root, link, va, vb = (rows[c].to_numpy() for c in ("root", "link", "va", "vb"))
        ends = np.flatnonzero(np.r_[root[1:] != root[:-1], True]) + 1
        for lo, hi in zip([0, *ends], ends):
            lists: dict = {k: {} for k in links}
            for k, x, y in zip(link[lo:hi].tolist(), va[lo:hi].tolist(), vb[lo:hi].tolist()):
                if k >= 0:
                    a, b = divmod(k, 64)
                    lists[a, b].setdefault(x, set()).add(y)
                    lists[b, a].setdefault(y, set()).add(x)
            one = Search(plan, {k: {v: frozenset(x) for v, x in d.items()} for k, d in lists.items()}, [_NONE] * plan.query.n, spec)
            one.roots([int(root[lo])], lambda image: None)
            count.update(one.count)
        return pd.DataFrame({"name": list(count), "n": list(count.values())})

    # roots that reach nothing are searched as well
    alone = cand[plan.order[0]].select(F.col("id").alias("root"), F.lit(-1).alias("link"), F.lit(0).cast("long").alias("va"), F.lit(0).cast("long").alias("vb"))
    parts = regions(index, plan, cand).unionByName(alone).withColumn("g", F.pmod(F.xxhash64("root"), F.lit(groups)))
    return parts.groupBy("g").applyInPandas(search, "name string, n long")


def kernel_counters(index, plan: MatchPlan, spec: MatchSpec, cand: list[DataFrame]) -> DataFrame:
    """name, n: the work of the search, summed over the tasks; by regions where the index is too large
    to be broadcast."""
    raw = kernel_packed(index, plan, spec, cand, counters=True)
    if raw is None:
        raw = region_counters(index, plan, spec, cand)
    return raw.groupBy("name").agg(F.sum("n").alias("n"))

"""Number of squares hub - via - other - via whose two via corners are twins: alike in label and arcs.

A pair (hub, other) with c common neighbours stands for c (c - 1) matches, so paths of two arcs are
only counted by their ends and never written. Hubs and others are dealt into blocks by a hash; each
two blocks meet in a task, which walks its paths some millions at a time. What moves are packed
keys: arcs of a hub's block once for each block of others and the other way round. The arcs of one
hub or one other are in one block.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import PropertyGraph, QueryGraph

#: About the most arcs of a block, the arcs that are packed at once, and the paths that are held at once.
ARCS, LOT, PATHS = 4_000_000, 1_000_000, 2_000_000
#: Vias are looked up in a table where their range is below this.
TABLE = 1 << 24
_WHOLE = "decimal(38,0)"


@dataclass(frozen=True)
class Side:
    """A kind of arcs that leads from a corner to both vias (onward) or from them to it."""

    elabel: str
    onward: bool

    def arcs(self, g: PropertyGraph) -> DataFrame:
        a, b = ("src", "dst") if self.onward else ("dst", "src")
        return g.edges.where(F.col("elabel") == self.elabel).select(F.col(a).cast("long").alias("hub"), F.col(b).cast("long").alias("via")).where("hub IS NOT NULL AND via IS NOT NULL")


def square_of(g: PropertyGraph, q: QueryGraph) -> tuple[Side, Side] | None:
    """Both sides if q is such a square, its hub and other can be no other corner's image, and the declared
    kinds of arcs imply all labels."""
    if not q.directed or not g.types or q.n != 4 or len(q.edges) != 4 or any(q.where) or q.cross or any(q.edge_where):
        return None
    if any((q.labels[a], q.labels[b]) != g.types.get(e) for a, b, e in q.edges):
        return None
    for x, y in ((0, 1), (0, 2), (0, 3)):
        for vias in ((x, y), tuple(v for v in range(4) if v not in (x, y))):
            ends = [v for v in range(4) if v not in vias]
            arcs = {end: [(e, a == end) for via in vias for a, b, e in q.edges if {a, b} == {end, via}] for end in ends}
            alike = all(len(found) == 2 and found[0] == found[1] for found in arcs.values())
            if alike and q.labels[vias[0]] == q.labels[vias[1]] and len(set(q.labels)) == 3:
                return Side(*arcs[ends[0]][0]), Side(*arcs[ends[1]][0])
    return None


def _coded(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Codes in the order of the values, below 2 ** 31, and what gives the values back."""
    lo = x.min()
    if int(x.max()) - int(lo) < 1 << 31:
        return x - lo, x[:1] * 0 + lo
    base, at = np.unique(x, return_inverse=True)
    return at.astype(np.int64), base


def _values(codes: np.ndarray, base: np.ndarray) -> np.ndarray:
    return codes + base[0] if len(base) == 1 else base[codes]


def _distinct(first: np.ndarray, second: np.ndarray) -> tuple[np.ndarray, int]:
    """Sorted distinct keys first * span + second of codes, and the span."""
    span = int(second.max()) + 1
    keys = first * span + second
    keys.sort()
    return keys[np.append(True, keys[1:] != keys[:-1])], span


def packed(hub: np.ndarray, via: np.ndarray) -> bytes:
    """Distinct pairs of a lot, which must not be empty."""
    (h, hubs), (v, vias) = _coded(hub), _coded(via)
    keys, span = _distinct(h, v)
    steps = np.diff(keys)
    least = np.min_scalar_type(int(steps.max())) if len(steps) else np.dtype(np.uint8)
    head = np.array([span, keys[0], len(hubs), len(vias), least.itemsize, len(steps)], dtype=np.int64)
    body = steps.astype(f"u{least.itemsize}").tobytes()
    return head.tobytes() + hubs.tobytes() + vias.tobytes() + pa.compress(body, codec="zstd", asbytes=True)


def unpacked(blob: bytes) -> tuple[np.ndarray, np.ndarray]:
    span, first, n, m, width, steps = map(int, np.frombuffer(blob, dtype=np.int64, count=6))
    hubs, vias = np.frombuffer(blob, dtype=np.int64, count=n, offset=48), np.frombuffer(blob, dtype=np.int64, count=m, offset=48 + 8 * n)
    body = pa.decompress(blob[48 + 8 * (n + m) :], decompressed_size=steps * width, codec="zstd", asbytes=True)
    keys = np.cumsum(np.append(first, np.frombuffer(body, dtype=f"u{width}").astype(np.int64)))
    h = keys // span
    return _values(h, hubs), _values(keys - h * span, vias)


def _all(blobs: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    sizes = np.cumsum([0, *(int(np.frombuffer(b, dtype=np.int64, count=6)[5]) + 1 for b in blobs)])
    hub, via = np.empty(sizes[-1], dtype=np.int64), np.empty(sizes[-1], dtype=np.int64)
    for lo, hi, blob in zip(sizes, sizes[1:], blobs):
        hub[lo:hi], via[lo:hi] = unpacked(blob)
    return hub, via


def squares_of(lines: list[bytes], others: list[bytes]) -> int:
    """The sum of c (c - 1) over the pairs of a hub and an other of two blocks."""
    if not lines or not others:
        return 0
    hub, via = _all(others)
    hub = _coded(hub)[0]
    via, base = _coded(via)
    keys, span = _distinct(via, hub)
    via = keys // span
    ends = (keys - via * span).astype(np.int32)  # the others next to each via, via by via
    starts = np.flatnonzero(np.append(True, via[1:] != via[:-1]))
    vias, stops = _values(via[starts], base), np.append(starts[1:], len(via))
    del hub, via, keys

    hub, via = _all(lines)
    hub = _coded(hub)[0]
    via, base = _coded(via)
    keys, width = _distinct(hub, via)
    hub = keys // width
    via = _values(keys - hub * width, base)
    del keys
    low, high = int(vias[0]), int(vias[-1])
    if high - low < TABLE:
        table = np.full(high - low + 1, -1, dtype=np.int32)
        table[vias - low] = np.arange(len(vias), dtype=np.int32)
        within = (via >= low) & (via <= high)
        at = np.where(within, table[np.where(within, via - low, 0)], -1)
        del within
    else:
        at = np.minimum(np.searchsorted(vias, via), len(vias) - 1)
        at = np.where(vias[at] == via, at, -1)
    hub, at = hub[at >= 0], at[at >= 0]
    same = hub[1:] == hub[:-1]
    if not same.any():  # one via makes no square
        return 0
    more = np.append(False, same) | np.append(same, False)
    hub, at = hub[more], at[more]
    del via, same, more
    first, number = starts[at], stops[at] - starts[at]
    begins = np.flatnonzero(np.append(True, hub[1:] != hub[:-1]))
    order = np.repeat(np.arange(len(begins)), np.diff(np.append(begins, len(hub))))
    before = np.append(0, np.cumsum(number))  # paths before each line
    bounds = np.append(begins, len(hub))
    marks, every = before[bounds], None
    total, k = 0, 0

    def reached(lo: int, hi: int) -> np.ndarray:
        n = number[lo:hi]
        return ends[np.repeat(first[lo:hi] - (before[lo:hi] - before[lo]), n) + np.arange(before[hi] - before[lo])]

    while k < len(begins):
        lo = bounds[k]
        last = int(np.searchsorted(marks, before[lo] + PATHS, side="right")) - 1
        if last > k:  # some hubs whole
            hi = bounds[last]
            pairs = np.repeat((order[lo:hi] - k) * span, number[lo:hi]) + reached(lo, hi)
            pairs.sort()
            runs = np.diff(np.append(np.flatnonzero(np.append(True, pairs[1:] != pairs[:-1])), len(pairs)))
            total += int((runs * (runs - 1)).sum())
            k = last
        else:  # a hub of very many paths
            every = np.unique(ends) if every is None else every
            hi, often = bounds[k + 1], np.zeros(len(every), dtype=np.int64)
            while lo < hi:
                to = min(hi, max(lo + 1, int(np.searchsorted(before, before[lo] + PATHS, side="right")) - 1))
                often += np.bincount(np.searchsorted(every, reached(lo, to)), minlength=len(every))
                lo = to
            total += int((often * (often - 1)).sum())
            k += 1
    return total


def squares(g: PropertyGraph, sides: tuple[Side, Side]) -> DataFrame:
    """n: the number of matches. Arcs that are there twice count once, so the graph need not be stored."""
    arcs = [side.arcs(g) for side in sides]
    blocks = [max(1, -(-df.count() // ARCS)) for df in arcs]

    def pack(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0

        def sent() -> pa.RecordBatch:
            hub, via, block = (np.concatenate([b.column(c).to_numpy() for b in held]) for c in ("hub", "via", "block"))
            own = np.unique(block)
            return pa.RecordBatch.from_pydict({"block": pa.array(own), "blob": pa.array([packed(hub[block == k], via[block == k]) for k in own], pa.binary())})

        for batch in batches:
            held.append(batch)
            size += batch.num_rows
            if size >= LOT:
                yield sent()
                held, size = [], 0
        if size:
            yield sent()

    def every(n: int) -> Column:
        return F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long")))

    lots = []
    for k, df in enumerate(arcs):
        mine, theirs = ("i", "j") if k == 0 else ("j", "i")
        blobs = df.withColumn("block", F.pmod(F.xxhash64("hub"), F.lit(blocks[k]).cast("long"))).mapInArrow(pack, "block long, blob binary")
        lots.append(blobs.select(F.col("block").alias(mine), F.lit(k).alias("side"), "blob", every(blocks[1 - k]).alias(theirs)).select("i", "j", "side", "blob"))

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: tuple[list, list] = [], []
        for batch in batches:
            for side, blob in zip(batch.column("side").to_pylist(), batch.column("blob").to_pylist()):
                found[side].append(blob)
        yield pa.RecordBatch.from_pydict({"n": [str(squares_of(*found))]})

    met = lots[0].unionByName(lots[1]).repartition(min(4096, blocks[0] * blocks[1]), "i", "j").groupBy("i", "j").applyInArrow(meet, "n string")
    return met.agg(F.coalesce(F.sum(F.col("n").cast(_WHOLE)), F.lit(0)).cast("long").alias("n"))


__all__ = ["Side", "packed", "square_of", "squares", "squares_of", "unpacked"]

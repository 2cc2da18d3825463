"""All triangles of a graph whose arcs follow from what its vertices hold, such as near vectors.

Vertices are dealt into blocks, and each three blocks meet in one task, which finds their arcs anew
and gives the triangles that have a corner in each. Neither arcs nor paths of two arcs are written
or moved: a vertex goes to b (b + 1) / 2 tasks, and the rows of the answer leave the task that made
them. A task holds one bit matrix of two blocks, whatever the number of triangles is.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: About the most vertices of a block.
BLOCK = 8192
#: Vertices whose arcs are found at once, pairs of neighbours tested at once, triangles sent at once.
ROWS, PAIRS, SENT = 256, 1 << 21, 1 << 18
#: The six orders of three corners.
_ORDERS = ("abc", "acb", "bac", "bca", "cab", "cba")


class Block:
    """Vertices of a block by id; rows of the same id are one vertex, linked if any of them is."""

    def __init__(self, ids: np.ndarray, values: np.ndarray):
        at = np.argsort(ids, kind="stable")
        self.ids, self.starts = np.unique(ids[at], return_index=True)
        self.values = values[at]
        self.ends = np.append(self.starts[1:], len(ids))

    def __len__(self) -> int:
        return len(self.ids)


def arcs_between(x: Block, lo: int, hi: int, y: Block, linked: Callable) -> np.ndarray:
    """Which of the vertices lo to hi of x are linked with which of y."""
    first = x.starts[lo]
    out = linked(x.values[first : x.ends[hi - 1]], y.values)
    if len(y) < len(y.values):
        out = np.logical_or.reduceat(out, y.starts, axis=1)
    return np.logical_or.reduceat(out, x.starts[lo:hi] - first, axis=0) if hi - lo < len(out) else out


def corners(x: Block, y: Block, z: Block, linked: Callable) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """Triangles with a corner in each block, each once: the corners a and b, where those of c begin, and c.

    Blocks may be the same; corners in one block come in its order.
    """
    if not (len(x) and len(y) and len(z)):
        return
    close = np.empty((len(y), len(z)), dtype=bool)
    for lo in range(0, len(y), ROWS):
        hi = min(lo + ROWS, len(y))
        close[lo:hi] = arcs_between(y, lo, hi, z, linked)
        if y is z:
            close[lo:hi] &= np.arange(len(z)) > np.arange(lo, hi)[:, None]
    for lo in range(0, len(x), ROWS):
        hi = min(lo + ROWS, len(x))
        to_y = arcs_between(x, lo, hi, y, linked)
        if x is y:
            to_y &= np.arange(len(y)) > np.arange(lo, hi)[:, None]
        to_z = to_y if y is z else arcs_between(x, lo, hi, z, linked)
        for a in range(hi - lo):
            b, c = np.flatnonzero(to_y[a]), np.flatnonzero(to_z[a])
            if not (len(b) and len(c)):
                continue
            step = max(1, PAIRS // len(c))
            for part in (b[k : k + step] for k in range(0, len(b), step)):
                met = close[part[:, None], c]
                often = met.sum(axis=1)
                some = np.flatnonzero(often)
                if len(some):
                    yield np.full(len(some), x.ids[lo + a]), y.ids[part[some]], often[some], z.ids[c[np.nonzero(met)[1]]]


def _sent(found: list[tuple]) -> pa.RecordBatch:
    a, b, often, c = (np.concatenate(p) for p in zip(*found))
    return pa.RecordBatch.from_pydict({"a": pa.array(a), "b": pa.array(b), "c": pa.ListArray.from_arrays(pa.array(np.append(0, np.cumsum(often)), pa.int32()), pa.array(c))})


def triangles(rows: DataFrame, linked: Callable[[np.ndarray, np.ndarray], np.ndarray], block: int = BLOCK) -> DataFrame:
    """a, b, c: three different vertices, in each order, each two of them linked.

    rows: id (long, not null), v (array of one length); linked(x, y): boolean matrix, symmetric, of the
    stacked values of two lots of rows.
    """
    n = rows.count()
    blocks = max(1, -(-n // block), min(4, n // 512))
    other = lambda lo: F.explode(F.sequence(lo, F.lit(blocks - 1).cast("long")))
    placed = rows.select("id", "v", F.pmod(F.xxhash64("id"), F.lit(blocks)).alias("x"))
    placed = placed.withColumn("y", other(F.lit(0).cast("long"))).withColumn("z", other(F.col("y")))
    placed = placed.select(F.concat_ws(":", F.transform(F.array_sort(F.array("x", "y", "z")), lambda k: k.cast("string"))).alias("t"), "x", "id", "v")
    tasks = blocks * (blocks + 1) * (blocks + 2) // 6

    def meet(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, values, at = [], [], []
        for batch in batches:
            ids.append(batch.column("id").to_numpy(zero_copy_only=False))
            at.append(batch.column("x").to_numpy(zero_copy_only=False))
            values.append(_stacked(batch.column("v")))
        ids, values, at = np.concatenate(ids), np.concatenate(values), np.concatenate(at)
        own = {k: Block(ids[at == k], values[at == k]) for k in map(int, key[0].as_py().split(":"))}
        found, size = [], 0
        for one in corners(*(own[int(k)] for k in key[0].as_py().split(":")), linked):
            found.append(one)
            size += len(one[3])
            if size >= SENT:
                yield _sent(found)
                found, size = [], 0
        if found:
            yield _sent(found)

    packed = placed.repartition(min(tasks, 4096), "t").groupBy("t").applyInArrow(meet, "a long, b long, c array<long>")
    turned = packed.select("a", "b", "c", F.explode(F.array(*map(F.lit, range(6)))).alias("o")).select("a", "b", "o", F.explode("c").alias("c"))

    def corner(at: int) -> Column:
        a, b = (F.col("o").isin([k for k, o in enumerate(_ORDERS) if o[at] == n]) for n in "ab")
        return F.when(a, F.col("a")).when(b, F.col("b")).otherwise(F.col("c"))

    return turned.select(*[corner(k).alias(n) for k, n in enumerate("abc")])


def _stacked(lists: pa.ListArray) -> np.ndarray:
    width = len(lists[0]) if len(lists) else 0
    if any(n != width for n in lists.value_lengths().to_pylist()):
        raise ValueError("vectors differ in length")
    return lists.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(lists), width)


__all__ = ["Block", "arcs_between", "corners", "triangles"]

"""Best-fit packing by bin completion over the histogram of piece lengths.

A length is an integer of at most the capacity, so the whole packing problem is a table of at
most `capacity` counts, whatever the number of documents. The plan is searched on that table;
documents then find their place by the rank they have among pieces of equal length.

Search: take the largest length left and complete its sequence. Completions come fullest first, out
of all sums that the stock can make, and only undominated ones count: none in which some items could
give way to one larger or equal item left in stock, or to which an item could be added. A completion is
first used as often as the stock allows, on the way back once; so the search is complete. A branch
ends when its waste, or the lower bound of what is left, cannot beat the incumbent, which starts as
best-fit decreasing. The search ends when the incumbent meets the lower bound or all branches are
done (the plan is then proven optimal), or after `search_nodes` completions: the plan then says that
it is not proven; it is whole and valid in any case.

Nulls: a null text is empty and so is one end id; a null doc_id stays null. Repeated rows are
packed once each. An empty table gives no rows. Other columns are ignored. Of a text of any length
only the ids of its own batch of texts are held, 4 bytes each.
"""

from __future__ import annotations

import itertools
import struct
import zlib
from collections import defaultdict
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe import encoder, groups
from .common import running_offsets, trim, written

Pattern = tuple[tuple[int, int], ...]  # (length, times), largest first


def lower_bound(counts: np.ndarray, capacity: int) -> int:
    """No packing has fewer bins: volume, and volume beside items too large to share a bin."""
    size = np.arange(capacity + 1)
    n, vol = np.append(np.cumsum(counts[::-1])[::-1], 0), np.cumsum(counts * size)
    half = capacity // 2
    # for each k: items over capacity - k stand alone as far as items of k or more go
    k = np.arange(half + 1)
    large = np.where(k > 0, n[capacity - k + 1], 0)
    mid = n[half + 1] - large
    mid_vol = vol[capacity - k] - vol[half]
    small_vol = vol[half] - np.where(k > 0, vol[k - 1], 0)
    beside = np.maximum(0, -(-(small_vol - (mid * capacity - mid_vol)) // capacity))
    return max(-(-int(vol[-1]) // capacity), int((large + mid + beside).max()))


def best_fit_decreasing(counts: np.ndarray, capacity: int) -> dict[Pattern, int]:
    """Best-fit decreasing on counts: bins of equal content move together."""
    open_bins: dict[int, list[list]] = defaultdict(list)  # room left -> [pattern, bins]
    rooms = np.zeros(capacity + 1, dtype=bool)
    for s in range(capacity, 0, -1):
        left = int(counts[s])
        while left:
            fits = np.flatnonzero(rooms[s:])
            if fits.size:
                room = s + int(fits[0])
                pattern, bins = open_bins[room].pop()
                rooms[room] = bool(open_bins[room])
            else:
                room, pattern, bins = capacity, (), -(-left // (capacity // s))
            per = room // s
            whole = min(bins, left // per)
            for times, n in ((per, whole), (left - whole * per, 1) if whole < bins and left > whole * per else (0, 0)):
                if n and times:
                    open_bins[room - s * times].append([(*pattern, (s, times)), n])
                    rooms[room - s * times] = True
                    left -= n * times
                    bins -= n
            if bins and pattern:
                open_bins[room].append([pattern, bins])
                rooms[room] = True
    out: dict[Pattern, int] = defaultdict(int)
    for held in open_bins.values():
        for pattern, n in held:
            out[pattern] += n
    return dict(out)


def undominated(items: Pattern, waste: int, spare: int) -> bool:
    """items: what completes a sequence and leaves `waste`; spare: bit x is set if a length x is left.

    Dominated: a part of the items (none, one or several) could give way to one spare item that is
    larger and still fits, or that takes the room of several.
    """
    none, one, more = 1, 0, 0  # sums of no, one, several items, as bits
    for s, times in items:
        for _ in range(times):
            more |= (more | one) << s
            one |= none << s
    if more & spare:
        return False
    return not any(((none | one | more) << d) & spare for d in range(1, waste + 1))


def completions(left: np.ndarray, room: int, most_waste: int) -> Iterator[tuple[Pattern, int] | None]:
    """(items, waste) that fill `room` from the counts left, least waste first and larger items first;
    None stands for one that is dominated, so that a caller may count it.

    reach[k] has a bit for each sum of lengths from the k-th on, so no step leads to a dead end.
    """
    sizes = [int(s) for s in np.flatnonzero(left[: room + 1])[::-1] if s]
    times = [min(int(left[s]), room // s) for s in sizes]
    mask, reach = (1 << room + 1) - 1, [1] * (len(sizes) + 1)
    for k in range(len(sizes) - 1, -1, -1):
        sums, n, step = reach[k + 1], times[k], 1
        while n > 0 and sums != mask:  # once every sum can be made, longer items change nothing
            sums |= (sums << sizes[k] * min(step, n)) & mask
            n, step = n - step, step * 2
        reach[k] = sums
    held = np.zeros(len(left) + -len(left) % 8, dtype=np.uint8)
    held[1 : len(left)] = left[1:] > 0
    stock = int.from_bytes(np.packbits(held, bitorder="little").tobytes(), "little")

    def exact(k: int, rest: int) -> Iterator[Pattern]:
        if not rest:
            yield ()
            return
        while k < len(sizes) and reach[k] >> rest & 1:
            s = sizes[k]
            for n in range(min(times[k], rest // s), 0, -1):
                if reach[k + 1] >> rest - s * n & 1:
                    for tail in exact(k + 1, rest - s * n):
                        yield ((s, n), *tail)
            k += 1

    for waste in range(min(room, most_waste) + 1):
        if reach[0] >> room - waste & 1:
            for items in exact(0, room - waste):
                spare = stock
                for s, n in items:
                    if n >= left[s]:
                        spare &= ~(1 << s)
                yield (items, waste) if undominated(items, waste, spare) else None


@dataclass(frozen=True)
class Plan:
    """Patterns and how many sequences follow each; `least` is a lower bound on `bins`."""

    patterns: dict[Pattern, int]
    bins: int
    least: int
    proven: bool


def plan(counts: np.ndarray, capacity: int, search_nodes: int = 4000) -> Plan:
    """A plan for counts[length] pieces of each length."""
    counts = counts.astype(np.int64)
    best = best_fit_decreasing(counts, capacity)
    bins, least = sum(best.values()), lower_bound(counts, capacity)
    total = int((counts * np.arange(capacity + 1)).sum())
    nodes, left = 0, counts.copy()
    levels: list[_Level] = []

    def enter(used: int, waste: int, applied) -> None:
        """A level for the counts left now, unless they are none or cannot lead to a better plan."""
        nonlocal best, bins
        stock = np.flatnonzero(left)
        if not stock.size:
            if used < bins:
                found: dict[Pattern, int] = defaultdict(int)
                for pattern, n in [*(v.applied for v in levels[1:]), applied]:
                    found[pattern] += n
                best, bins = dict(found), used
        elif used + lower_bound(left, capacity) < bins and waste <= (bins - 1) * capacity - total:
            levels.append(_Level(int(stock[-1]), used, waste, applied))
            if len(levels) > _HELD_LEVELS:  # its completions are made again if the search comes back
                levels[-1 - _HELD_LEVELS].todo = None
            return
        _move(left, applied, 1)

    if bins > least:
        enter(0, 0, None)
    while levels and bins > least and nodes < search_nodes:
        v = levels[-1]
        if v.once:  # the same completion again, this time for one sequence only
            pattern, n, lost = v.once.pop()
        else:
            if v.todo is None:
                rest = left.copy()
                rest[v.top] -= 1
                # waste that a better plan may have from here on
                v.todo = itertools.islice(completions(rest, capacity - v.top, (bins - 1) * capacity - total - v.waste), v.seen, None)
            got = next(v.todo, StopIteration)
            nodes += 1
            v.seen += 1
            if got is StopIteration:
                levels.pop()
                _move(left, v.applied, 1)
                continue
            if got is None:
                continue
            need = defaultdict(int, got[0])
            need[v.top] += 1
            pattern, lost = tuple(sorted(need.items(), reverse=True)), got[1]
            n = min(int(left[s]) // k for s, k in pattern)
            if n > 1:
                v.once.append((pattern, 1, lost))
        if v.waste + n * lost <= (bins - 1) * capacity - total:
            _move(left, (pattern, n), -1)
            enter(v.used + n, v.waste + n * lost, (pattern, n))
    return Plan(best, bins, least, bins <= least or not levels)


#: Levels of the search that keep their completions at hand; the others hold a few numbers each.
_HELD_LEVELS = 8


class _Level:
    """A place of the search: the largest length left, what led here, and the completions seen so far."""

    def __init__(self, top: int, used: int, waste: int, applied):
        self.top, self.used, self.waste, self.applied = top, used, waste, applied
        self.todo, self.seen, self.once = None, 0, []


def _move(left: np.ndarray, applied, sign: int) -> None:
    if applied is not None:
        for s, k in applied[0]:
            left[s] += sign * k * applied[1]


class Places:
    """Where the r-th piece of each length goes; size bounded by the plan, not by documents."""

    def __init__(self, patterns: dict[Pattern, int]):
        seg = defaultdict(list)
        bin_no, given = 0, defaultdict(int)
        for pattern, n in sorted(patterns.items(), reverse=True):
            off = 0
            for s, times in pattern:
                seg[s].append((given[s], bin_no, times, off))
                given[s] += n * times
                off += s * times
            bin_no += n
        self.bins = bin_no
        self.seg = {s: np.array(x, dtype=np.int64).T for s, x in seg.items()}

    def find(self, length: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        seq, off = np.empty_like(rank), np.empty_like(rank)
        order = np.argsort(length, kind="stable")
        for rows in np.split(order, np.flatnonzero(np.diff(length[order])) + 1):
            if rows.size:
                s = int(length[rows[0]])
                start, first, times, base = self.seg[s]
                k = np.searchsorted(start, rank[rows], side="right") - 1
                r = rank[rows] - start[k]
                seq[rows], off[rows] = first[k] + r // times[k], base[k] + (r % times[k]) * s
        return seq, off


_PIECES = "part int, doc_id long, piece int, start long, length int, ids_crc32 long, nth long"


def cut_pieces(docs: DataFrame, tokenizer: str, end_id: int, capacity: int) -> DataFrame:
    """One row for each piece, with its rank among pieces of its length in its partition."""

    def cut(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, enc, end = TaskContext.get().partitionId(), encoder(tokenizer, 400_000), struct.pack("<I", end_id)
        seen = [0] * (capacity + 1)
        for b in batches:
            texts, ids = b.column(1).to_pylist(), b.column(0).to_pylist()
            for lo, hi in groups(texts):
                rows = []
                for d, x in zip(ids[lo:hi], enc.encode(texts[lo:hi])):
                    x += end
                    for p, at in enumerate(range(0, len(x), 4 * capacity)):
                        piece = x[at : at + 4 * capacity]
                        n = len(piece) // 4
                        rows.append((part, d, p, at // 4, n, zlib.crc32(piece), seen[n]))
                        seen[n] += 1
                cols = list(zip(*rows))
                kinds = (pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], ["part", "doc_id", "piece", "start", "length", "ids_crc32", "nth"])

    return docs.select("doc_id", "text").mapInArrow(cut, _PIECES)


def pack(docs: DataFrame, tokenizer: str, end_id: int = 1, capacity: int = 4096, search_nodes: int = 4000) -> DataFrame:
    """Pack (doc_id, text) into few sequences of at most `capacity` ids.

    Returns doc_id, piece, start, length, ids_crc32, sequence_id, offset.
    """
    trim()
    pieces = written(cut_pieces(docs, tokenizer, end_id, capacity), "pieces")
    by_part = pieces.groupBy("part", "length").agg(F.count("*").alias("n"))
    counts = np.zeros(capacity + 1, dtype=np.int64)
    for r in by_part.groupBy("length").agg(F.sum("n").alias("n")).collect():  # at most `capacity` rows
        counts[r.length] = r.n
    places = Places(plan(counts, capacity, search_nodes).patterns)
    ranked = pieces.join(running_offsets(by_part, ["length"], "part", ["n"]), ["length", "part"]).select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("nth") + F.col("n_before")).alias("nth"))
    shared = docs.sparkSession.sparkContext.broadcast(places)

    def place(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            length = b.column(3).to_numpy(zero_copy_only=False).astype(np.int64)
            seq, off = shared.value.find(length, b.column(5).to_numpy(zero_copy_only=False).astype(np.int64))
            yield pa.RecordBatch.from_arrays([*(b.column(i) for i in range(3)), pa.array(length), b.column(4), pa.array(seq), pa.array(off)], ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return ranked.mapInArrow(place, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")

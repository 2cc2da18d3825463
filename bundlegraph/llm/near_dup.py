"""Near-duplicate detection: minhash with tensored banding, exact links, exact components.

Sets: distinct shingles of `words` words (ASCII-lower-cased runs of non-white-space), kept as
64-bit hashes; a shorter text is one shingle. Documents with equal sets are one class from the
start (128-bit key), so copies never meet again.

Tensored banding: two collections of `tables` sub-keys each, every sub-key made of `rows`
minhashes. A table is a pair of sub-keys, one of each collection, so tables**2 tables cost only
2 * tables * rows minhashes. Two sets meet if they share a sub-key of both collections.

Links: first each member of a bucket is compared on full sets with the bucket's smallest member,
and the links give components; a group of copies mostly falls into one. Buckets that still hold
two components are open. What open buckets tie together is a cluster, and in a cluster each pair
of two components is compared, block against block within tasks: only links leave a task, never
pairs, and blocks of one component are not compared with each other. So every pair that meets in
a bucket is compared or already connected, and no bucket is capped.

Nulls: null and blank texts have no shingles and are linked with nothing; rows with a null
doc_id are returned alone with a null component. doc_id is the identity of a document; repeated
rows share a component, and rows of one doc_id with different texts are each compared. Empty tables
give no rows. Other columns are ignored. A very long text is one set of 8 bytes a shingle.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import take_over, trim, written
from .components import connected

_ALL = (1 << 64) - 1
_LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
_ODD = np.random.default_rng(20240229).integers(1, 1 << 63, 4096, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


class _WordHashes(dict):
    def __missing__(self, w: bytes) -> int:
        import xxhash

        if len(self) > 600_000:
            self.clear()
        v = self[w] = xxhash.xxh3_64_intdigest(w)
        return v


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def shingle_set(text: str | None, words: int, known: dict) -> np.ndarray:
    """Sorted distinct shingle hashes of a whole text."""
    found = (text or "").encode("utf-8", "surrogatepass").translate(_LOWER).split()
    if not found:
        return np.empty(0, dtype=np.uint64)
    h = np.fromiter(map(known.__getitem__, found), dtype=np.uint64, count=len(found))
    width = min(words, len(h))
    n = len(h) - width + 1
    x = np.full(n, (width * int(_ODD[4000])) & _ALL, dtype=np.uint64)
    for i in range(width):
        x += _mix(h[i : i + n] + _ODD[4001 + i]) * _ODD[i]
    return np.unique(_mix(x))


def set_key(shingles: np.ndarray) -> tuple[int, int]:
    import xxhash

    raw = xxhash.xxh3_128_intdigest(shingles.tobytes())
    return (raw >> 64) - (1 << 63), (raw & _ALL) - (1 << 63)


def sub_keys(shingles: np.ndarray, tables: int, rows: int) -> np.ndarray:
    """2 * tables sub-keys (as signed integers), first one collection, then the other."""
    n = 2 * tables * rows
    mult, flip = _ODD[8 : 8 + n, None], _ODD[2000 : 2000 + n, None]
    low = np.full(n, np.iinfo(np.uint64).max, dtype=np.uint64)
    for lo in range(0, len(shingles), 2048):
        np.minimum(low, ((shingles[None, lo : lo + 2048] ^ flip) * mult).min(axis=1), out=low)
    low = _mix(low).reshape(2 * tables, rows)
    return _mix((low * _ODD[3900 : 3900 + rows]).sum(axis=1, dtype=np.uint64)).view(np.int64)


def signatures(docs: DataFrame, words: int, tables: int, rows: int) -> DataFrame:
    """doc_id, n, k1, k2 (the set's key), a, b (sub-keys of the two collections)."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        take_over("near_dup", lambda: None)
        known = _WordHashes()
        for batch in batches:
            n, k1, k2, a, b = [], [], [], [], []
            for t in batch.column(1):
                s = shingle_set(t.as_py(), words, known)
                n.append(len(s))
                k = set_key(s)
                k1.append(k[0])
                k2.append(k[1])
                keys = sub_keys(s, tables, rows) if len(s) else None
                a.append(None if keys is None else keys[:tables])
                b.append(None if keys is None else keys[tables:])
            longs = pa.list_(pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(k1, pa.int64()), pa.array(k2, pa.int64()), pa.array(a, longs), pa.array(b, longs)], ["doc_id", "n", "k1", "k2", "a", "b"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n long, k1 long, k2 long, a array<long>, b array<long>")


def full_sets(docs: DataFrame, wanted: DataFrame, words: int) -> DataFrame:
    """rep, shingles of the documents in wanted (rep, w1, w2), made again from their texts."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        take_over("near_dup", lambda: None)
        known = _WordHashes()
        for batch in batches:
            ids, sets = [], []
            for d, t, w1, w2 in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2).to_pylist(), batch.column(3).to_pylist()):
                s = shingle_set(t.as_py(), words, known)
                if set_key(s) == (w1, w2):
                    ids.append(d)
                    sets.append(s.view(np.int64))
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(sets, pa.list_(pa.int64()))], ["rep", "shingles"])

    texts = docs.select("doc_id", "text").join(wanted, F.col("doc_id") == F.col("rep")).select("doc_id", "text", "w1", "w2")
    return texts.mapInArrow(run, "rep long, shingles array<long>")


def buckets(reps: DataFrame) -> DataFrame:
    """key, rep, n of the buckets with two sets or more; of buckets with equal members one stays."""
    first = reps.select("rep", "n", "b", F.posexplode("a").alias("i", "ka"))
    shared = first.groupBy("i", "ka").agg(F.count("*").alias("c")).where("c > 1").select("i", "ka")
    pairs = first.join(shared, ["i", "ka"]).select("rep", "n", "i", "ka", F.posexplode("b").alias("j", "kb")).select("rep", "n", F.xxhash64("i", "ka", "j", "kb").alias("key"))
    rows = written(pairs, "bucket-rows")
    full = rows.groupBy("key").agg(F.count("*").alias("c"), F.min("rep").alias("low"), F.sum(F.xxhash64("rep").cast("decimal(38,0)")).alias("mark")).where("c > 1")
    one = full.groupBy("c", "low", "mark").agg(F.min("key").alias("key")).select("key")
    return rows.join(one, "key")


def verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """a, b of the pairs whose full sets are similar enough."""
    left = sets.select(F.col("rep").alias("a"), F.col("shingles").alias("sa"))
    right = sets.select(F.col("rep").alias("b"), F.col("shingles").alias("sb"))
    both = pairs.join(left, "a").join(right, "b").select("a", "b", (F.size("sa") + F.size("sb")).alias("s"), F.size(F.array_intersect("sa", "sb")).alias("i"))
    return both.where(F.col("i") * 100 >= F.lit(percent) * (F.col("s") - F.col("i"))).select("a", "b")


def cross_links(inside: DataFrame, sets: DataFrame, percent: int, room: int = 200_000) -> DataFrame:
    """inside: rep, comp, cluster. a, b: pairs of components of a cluster with a link between them.

    Members are dealt into blocks of about `room` shingles. Large components have blocks of their
    own, small ones share some; every two blocks of a cluster meet in one task, but for two of the
    same large component.
    """
    rows = written(inside.join(sets, "rep").select("rep", "comp", "cluster", "shingles", F.size("shingles").alias("n")), "members")
    comp_size = rows.groupBy("cluster", "comp").agg(F.sum("n").alias("w"))
    small = comp_size.where(F.col("w") < room).groupBy("cluster").agg(F.ceil(F.sum("w") / room).cast("int").alias("shared"))
    plan = comp_size.join(small, "cluster", "left")
    own = F.when(F.col("w") >= room, F.ceil(F.col("w") / room).cast("int"))
    # a block: (own component or null, number)
    plan = written(plan.select("cluster", "comp", own.alias("parts"), F.coalesce("shared", F.lit(1)).alias("shared")), "blocks")
    block = F.when(F.col("parts").isNull(), F.struct(F.lit(None).cast("long").alias("of"), F.pmod(F.xxhash64("comp"), F.col("shared")).cast("int").alias("no"))).otherwise(F.struct(F.col("comp").alias("of"), F.pmod(F.xxhash64("rep"), F.col("parts")).cast("int").alias("no")))
    placed = rows.join(plan, ["cluster", "comp"]).select("cluster", "rep", "comp", "shingles", block.alias("block"))
    last = F.coalesce("parts", "shared") - 1
    blocks = plan.select("cluster", F.when(F.col("parts").isNotNull(), F.col("comp")).alias("of"), last.alias("last")).distinct().select("cluster", "of", F.explode(F.sequence(F.lit(0), F.col("last"))).alias("no")).select("cluster", F.struct("of", "no").alias("block"))
    blocks = written(blocks, "block-list")
    other = blocks.select("cluster", F.col("block").alias("block2"))
    meet = blocks.join(other, "cluster").where((F.col("block") <= F.col("block2")) & ~F.coalesce(F.col("block.of") == F.col("block2.of"), F.lit(False)))
    meet = written(meet, "meetings")

    def compare(x, y):
        import pandas as pd

        none = pd.DataFrame({"a": pd.Series(dtype="int64"), "b": pd.Series(dtype="int64")})
        if not len(x) or not len(y):
            return none
        sets_y = [s.view(np.uint64) for s in y["rs"]]
        flat = np.concatenate(sets_y)
        size_y = np.array([len(s) for s in sets_y])
        at = np.cumsum(size_y) - size_y
        known, where = np.unique(flat, return_inverse=True)
        comp_y, out = y["rc"].to_numpy(), set()
        for comp, s in zip(x["lc"].to_numpy(), x["ls"]):
            s = s.view(np.uint64)
            if not ((size_y * 100 >= len(s) * percent) & (comp_y != comp)).any():
                continue
            pos = np.searchsorted(known, s)
            pos[pos == len(known)] = 0
            mark = np.zeros(len(known), dtype=np.int32)
            mark[pos[known[pos] == s]] = 1
            common = np.add.reduceat(mark[where], at)
            hit = (comp_y != comp) & (common * 100 >= percent * (size_y + len(s) - common))
            out |= {(min(comp, c), max(comp, c)) for c in comp_y[hit].tolist()}
        return pd.DataFrame(sorted(out), columns=["a", "b"]).astype("int64") if out else none

    keys = ["cluster", "block", "block2"]
    left = placed.join(meet, ["cluster", "block"]).select(*keys, "comp", "shingles")
    right = placed.withColumnRenamed("block", "block2").join(meet, ["cluster", "block2"]).select(*keys, "comp", "shingles")
    tag = F.concat_ws("|", F.col("cluster").cast("string"), F.to_json("block"), F.to_json("block2")).alias("k")
    left = left.select(tag, F.col("comp").alias("lc"), F.col("shingles").alias("ls"))
    right = right.select(tag, F.col("comp").alias("rc"), F.col("shingles").alias("rs"))
    return left.groupBy("k").cogroup(right.groupBy("k")).applyInPandas(compare, "a long, b long").distinct()


def near_duplicates(docs: DataFrame, words: int = 5, percent: int = 80, tables: int = 12, rows: int = 3) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest doc_id reachable), kept."""
    trim()
    sig = written(signatures(docs, words, tables, rows), "signatures")
    real = sig.where("n > 0 AND doc_id IS NOT NULL")
    classes = written(real.groupBy("k1", "k2").agg(F.min("doc_id").alias("rep")), "classes")
    reps = real.join(classes.withColumnsRenamed({"k1": "w1", "k2": "w2"}), (F.col("doc_id") == F.col("rep")) & (F.col("k1") == F.col("w1")) & (F.col("k2") == F.col("w2"))).select("rep", "n", "w1", "w2", "a", "b")
    held = written(buckets(reps.select("rep", "n", "a", "b").dropDuplicates(["rep", "n", "a", "b"])), "buckets")
    wanted = held.select("rep").distinct().join(classes.select("rep", F.col("k1").alias("w1"), F.col("k2").alias("w2")), "rep")
    sets = written(full_sets(docs, wanted, words), "sets")

    # stars: every member against the smallest one of its bucket
    low = held.groupBy("key").agg(F.min_by(F.struct("rep", "n"), "rep").alias("l")).select("key", F.col("l.rep").alias("l_rep"), F.col("l.n").alias("l_n"))
    near = F.least("n", "l_n") * 100 >= F.greatest("n", "l_n") * percent  # else too unequal in size to be linked
    stars = held.join(low, "key").where((F.col("rep") != F.col("l_rep")) & near).select(F.col("l_rep").alias("a"), F.col("rep").alias("b")).distinct()
    comps = written(connected(verified(stars, sets, percent)), "comps")

    # open buckets: two components or more
    of = comps.withColumnRenamed("node", "rep")
    members = held.select("key", "rep").join(of, "rep", "left").select("key", "rep", F.coalesce("comp", "rep").alias("comp"))
    open_ = members.groupBy("key").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo <> hi").select("key", "lo")
    opened = written(members.join(open_, "key"), "open-buckets")
    ties = written(connected(opened.select(F.col("comp").alias("a"), F.col("lo").alias("b"))), "ties")
    inside = opened.select("rep", "comp").distinct().join(ties.select(F.col("node").alias("comp"), F.col("comp").alias("cluster")), "comp")
    links = written(cross_links(inside, sets, percent), "cross-links")
    up = connected(links)
    moved = comps.join(up.select(F.col("node").alias("m"), F.col("comp").alias("to")), F.col("comp") == F.col("m"), "left").select("node", F.coalesce("to", "comp").alias("comp"))
    comps = written(moved.unionByName(up.join(comps, "node", "left_anti").select("node", "comp")), "all-comps")

    of_rep = classes.join(comps.withColumnRenamed("node", "rep"), "rep", "left").select("k1", "k2", F.coalesce("comp", "rep").alias("component_id"))
    known = sig.select("doc_id", "n", "k1", "k2")
    linked = known.where("n > 0 AND doc_id IS NOT NULL").join(of_rep, ["k1", "k2"]).select("doc_id", "n", "component_id")
    alone = known.where("n = 0 OR doc_id IS NULL").select("doc_id", "n", F.col("doc_id").alias("component_id"))
    return linked.unionByName(alone).select("doc_id", F.col("n").alias("n_shingles"), "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept"))


REPORT_SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 4 THEN [array_to_string(w, ' ')]
  ELSE list_transform(range(1, len(w) - 2), lambda i: array_to_string(w[i:i+3], ' ')) END) AS g FROM w),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS i FROM s x JOIN s y ON x.g = y.g AND x.doc_id <> y.doc_id GROUP BY 1, 2),
l AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * i >= 80 * (x.n + y.n - i)),
r AS (SELECT doc_id AS a, doc_id AS b FROM w UNION SELECT r.a, l.b FROM r JOIN l ON r.b = l.a)
SELECT w.doc_id, coalesce(n.n, 0) AS n_shingles, c.component_id, w.doc_id = c.component_id AS kept
FROM w JOIN (SELECT a, min(b) AS component_id FROM r GROUP BY a) c ON c.a = w.doc_id LEFT JOIN n ON n.doc_id = w.doc_id
"""

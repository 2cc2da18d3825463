"""Patterns over arriving edges and events, on Structured Streaming."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..model import QueryGraph


def join_arcs(q: QueryGraph, arcs: list[DataFrame], vertices: DataFrame, first: int = 0) -> DataFrame:
    """Matches with one arc table for each query arc, joined from arc `first` outwards (connected, iso)."""

    def bound(k: int) -> DataFrame:
        a, b, e = q.edges[k]
        t = arcs[k] if e is None else arcs[k].where(F.col("elabel") == e)
        return t.where("src <> dst").select(F.col("src").alias(q.names[a]), F.col("dst").alias(q.names[b])).distinct()

    df, left = bound(first), [k for k in range(len(q.edges)) if k != first]
    while left:
        k = next(k for k in left if {q.names[q.edges[k][0]], q.names[q.edges[k][1]]} & set(df.columns))
        t = bound(k)
        df = df.join(t, [c for c in t.columns if c in df.columns])
        left.remove(k)
    for i in range(q.n):
        if q.labels[i] is not None:
            df = df.join(vertices.where(F.col("label") == q.labels[i]).select(F.col("id").alias(q.names[i])).distinct(), q.names[i], "left_semi")
        for j in range(i):
            if q.may_clash(i, j):
                df = df.where(F.col(q.names[i]) != F.col(q.names[j]))
    return df.select(*q.names)


def delta_matches(q: QueryGraph, old: DataFrame, new: DataFrame, vertices: DataFrame) -> DataFrame:
    """Matches that use a new arc: the k-th term takes arc k from the new ones, earlier arcs from the
    old ones and later arcs from both, so no match is made twice. old and new share no arc."""
    both = old.unionByName(new)
    terms = [join_arcs(q, [old if j < k else new if j == k else both for j in range(len(q.edges))], vertices, first=k) for k in range(len(q.edges))]
    return reduce(DataFrame.unionByName, terms)


def stream_match(edges: DataFrame, vertices: DataFrame, q: QueryGraph, folder: str, checkpoint: str) -> StreamingQuery:
    """edges: a stream of src, dst, elabel. New matches go to folder/matches/batch=N.

    The arcs so far are kept in folder/arcs/batch=N. A batch that runs again replaces its own
    folders and looks at earlier ones only, so results are written exactly once.
    """
    spark = edges.sparkSession
    arc_schema = "src bigint, dst bigint, elabel string"

    def step(batch: DataFrame, n: int) -> None:
        jvm = spark.sparkContext._jvm
        fs_path = jvm.org.apache.hadoop.fs.Path(f"{folder}/arcs")
        some = fs_path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(fs_path)
        old = spark.read.schema(arc_schema + ", batch bigint").option("basePath", f"{folder}/arcs").parquet(f"{folder}/arcs").where(F.col("batch") < n).drop("batch") if some else spark.createDataFrame([], arc_schema)
        seen = old.select(F.col("src").alias("s"), F.col("dst").alias("d"), F.col("elabel").alias("e"))
        new = batch.select("src", "dst", "elabel").distinct().join(seen, (F.col("src") == F.col("s")) & (F.col("dst") == F.col("d")) & F.col("elabel").eqNullSafe(F.col("e")), "left_anti")
        new.write.mode("overwrite").parquet(f"{folder}/arcs/batch={n}")
        fresh = spark.read.schema(arc_schema).parquet(f"{folder}/arcs/batch={n}")
        delta_matches(q, old, fresh, vertices).write.mode("overwrite").parquet(f"{folder}/matches/batch={n}")

    return edges.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def temporal_pairs(events: DataFrame, first: str, then: str, within: str = "10 minutes", late: str | None = "1 hour") -> DataFrame:
    """user_id, first_id, then_id: an event of type `first` and one of type `then` of the same user
    after it, within a time. Works on a stream (both sides watermarked) and on a table."""
    a = events.where(F.col("event_type") == first).select("user_id", F.col("event_id").alias("first_id"), F.col("ts").alias("first_ts"))
    b = events.where(F.col("event_type") == then).select(F.col("user_id").alias("then_user"), F.col("event_id").alias("then_id"), F.col("ts").alias("then_ts"))
    if events.isStreaming and late:
        a, b = a.withWatermark("first_ts", late), b.withWatermark("then_ts", late)
    return a.join(b, (F.col("user_id") == F.col("then_user")) & (F.col("then_ts") > F.col("first_ts")) & (F.col("then_ts") <= F.col("first_ts") + F.expr(f"interval {within}"))).select("user_id", "first_id", "then_id")


def binned_pairs(events: DataFrame, first: str, then: str, seconds: int = 600) -> DataFrame:
    """The same on a table by time bins: an equi-join on (user, bin), so a hot user is cut by time."""
    a = events.where(F.col("event_type") == first).select("user_id", F.col("event_id").alias("first_id"), F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    b = events.where(F.col("event_type") == then).select("user_id", F.col("event_id").alias("then_id"), F.unix_micros(F.col("ts").cast("timestamp")).alias("u"))
    span = seconds * 1_000_000
    a = a.withColumn("bin", F.explode(F.array((F.col("t") / span).cast("long"), (F.col("t") / span).cast("long") + 1)))
    b = b.withColumn("bin", (F.col("u") / span).cast("long"))
    return a.join(b, ["user_id", "bin"]).where((F.col("u") > F.col("t")) & (F.col("u") <= F.col("t") + span)).select("user_id", "first_id", "then_id")


def temporal_triples(events: DataFrame, types: tuple[str, str, str], within: str = "10 minutes", late: str | None = "1 hour") -> DataFrame:
    """user_id, first_id, then_id, last_id: three events of a user in order, each within a time of the
    one before. Two interval joins on the user; on a stream all three sides are watermarked."""
    sides = []
    for k, kind in enumerate(types):
        e = events.where(F.col("event_type") == kind).select(F.col("user_id").alias(f"u{k}"), F.col("event_id").alias(f"e{k}"), F.col("ts").alias(f"t{k}"))
        sides.append(e.withWatermark(f"t{k}", late) if events.isStreaming and late else e)
    near = lambda k: (F.col(f"u{k}") == F.col(f"u{k - 1}")) & (F.col(f"t{k}") > F.col(f"t{k - 1}")) & (F.col(f"t{k}") <= F.col(f"t{k - 1}") + F.expr(f"interval {within}"))
    rows = sides[0].join(sides[1], near(1)).join(sides[2], near(2))
    return rows.select(F.col("u0").alias("user_id"), F.col("e0").alias("first_id"), F.col("e1").alias("then_id"), F.col("e2").alias("last_id"))


def late_rows(query: StreamingQuery) -> int:
    """Rows that a stream's stateful operators left out for coming after the watermark, so far."""
    return sum(op.get("numRowsDroppedByWatermark", 0) for p in query.recentProgress for op in p["stateOperators"])


def window_counts(events: DataFrame, size: str = "1 hour", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Events by window and type; tumbling without slide."""
    e = events.withWatermark("ts", late) if events.isStreaming else events
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return e.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """Sessions of each user: start, end, events."""
    e = events.withWatermark("ts", late) if events.isStreaming else events
    return e.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def new_arcs(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """src, dst, elabel of each user's first event on a key within the watermark."""
    e = events.select(F.col("user_id").alias("src"), F.get_json_object("props", "$.k").cast("long").alias("dst"), F.col("event_type").alias("elabel"), "ts")
    return (e.withWatermark("ts", late).dropDuplicatesWithinWatermark(["src", "dst", "elabel"]) if e.isStreaming else e.dropDuplicates(["src", "dst", "elabel"])).select("src", "dst", "elabel")


def chains(events: DataFrame, types: list[str], late: str | None = None, idle: str = "1 day") -> DataFrame:
    """user_id, n: how often a user's events ran through `types` in order (others may lie between).

    Without `late`, events of a batch are taken in time order as they come; state is one place and one
    count for each user. With `late`, events wait in the state until the watermark has passed them, so
    that those which come out of order across batches are still taken in time order; a user without
    events for `idle` leaves the state.
    """
    span = pd.Timedelta(idle)

    def advance(at: int, n: int, kinds) -> tuple[int, int]:
        for kind in kinds:
            if kind == types[at]:
                at += 1
                if at == len(types):
                    at, n = 0, n + 1
        return at, n

    def step(key: tuple, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        at, n = state.get if state.exists else (0, 0)
        state.update(advance(at, n, pd.concat(list(parts)).sort_values(["ts", "event_id"])["event_type"]))
        yield pd.DataFrame({"user_id": [key[0]], "n": [state.get[1]]})

    def wait(key: tuple, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        at, n, last, held = state.get if state.exists else (0, 0, 0, [])
        mark = state.getCurrentWatermarkMs()
        held = [tuple(h) for h in held]
        if not state.hasTimedOut:
            for p in parts:
                held += list(zip((p["ts"].astype("int64") // 10**3 if p["ts"].dtype == "datetime64[ns]" else p["ts"].astype("datetime64[us]").astype("int64")).tolist(), p["event_id"].tolist(), p["event_type"].tolist()))
        held.sort()
        ripe = [h for h in held if h[0] <= mark * 1000]
        held = held[len(ripe):]
        at, n = advance(at, n, [h[2] for h in ripe])
        last = max([last, *(h[0] for h in ripe)])
        if not held and last + span.value // 1000 <= mark * 1000:
            state.remove()
        else:
            state.update((at, n, last, held))
            state.setTimeoutTimestamp(max(mark + 1, (held[0][0] // 1000 + 1) if held else last // 1000 + span.value // 10**6))
        if ripe:
            yield pd.DataFrame({"user_id": [key[0]], "n": [n]})

    out = "user_id bigint, n bigint"
    rows = events.select("user_id", "event_id", "ts", "event_type")
    if late is None:
        return rows.groupBy("user_id").applyInPandasWithState(step, out, "at int, n bigint", "update", "NoTimeout")
    held = "at int, n bigint, last bigint, held array<struct<t: bigint, id: bigint, kind: string>>"
    return rows.withWatermark("ts", late).groupBy("user_id").applyInPandasWithState(wait, out, held, "update", "EventTimeTimeout")

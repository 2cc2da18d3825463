"""What a run cost: time split, memory, shuffle, and the report tables built from runs."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions.deadline import within

RUNS = (
    "method string, query string, size int, repeat int, pre_ms double, enum_ms double, total_ms double, timed_out boolean, n long, "
    "driver_mb double, jvm_mb double, shuffle_mb double, spill_mb double, rows_read long, stages int, tasks long, execution_mb double"
)


class RunMeter:
    """Peaks and totals of what happens between its making and `read`."""

    def __init__(self, spark: SparkSession):
        self.spark = spark
        self.first = max((s.stageId() for s in self._stages()), default=-1)
        try:  # the kernel's high-water mark of this process starts anew
            with open("/proc/self/clear_refs", "w") as f:
                f.write("5")
        except OSError:
            pass
        for pool in self._pools():
            pool.resetPeakUsage()

    def _pools(self) -> list:
        beans = self.spark.sparkContext._jvm.java.lang.management.ManagementFactory.getMemoryPoolMXBeans()
        return [b for b in beans if str(b.getType().toString()).lower().startswith("heap")]

    def _stages(self):
        sc = self.spark.sparkContext
        found = sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(sc._jvm.double, 0), None)
        return [found.apply(i) for i in range(found.size())]

    def read(self) -> tuple:
        """driver_mb, jvm_mb, shuffle_mb, spill_mb, rows_read, stages, tasks, execution_mb of this run's own stages."""
        mine = [s for s in self._stages() if s.stageId() > self.first]
        try:
            with open("/proc/self/status") as f:
                peak = next((int(line.split()[1]) / 1024 for line in f if line.startswith("VmHWM")), 0.0)
        except OSError:
            peak = 0.0
        jvm = sum(b.getPeakUsage().getUsed() for b in self._pools()) / 1e6
        return (
            peak, jvm, sum(s.shuffleWriteBytes() for s in mine) / 1e6, sum(s.memoryBytesSpilled() for s in mine) / 1e6,
            sum(s.inputRecords() + s.shuffleReadRecords() for s in mine), len(mine), sum(s.numCompleteTasks() for s in mine),
            max((s.peakExecutionMemory() for s in mine), default=0) / 1e6,
        )


def timed(spark: SparkSession, method: str, query: str, size: int, run: Callable[[], tuple[float, DataFrame]], cap_s: float | None = None, repeat: int = 0) -> tuple:
    """One row of RUNS. run() prepares and returns (preparation in ms, one-row count); a run whose
    time is over is cancelled, counts as the cap, and has no n."""
    meter, began, seen = RunMeter(spark), time.time(), {"pre": 0.0}

    def action() -> int:
        seen["pre"], counted = run()
        return int(counted.first()[0])

    n, out = within(spark, cap_s, action)
    total = cap_s * 1e3 if out else (time.time() - began) * 1e3
    pre = min(float(seen["pre"]), total)
    return method, query, size, repeat, pre, total - pre, total, out, n, *meter.read()


def per_query(runs: DataFrame) -> DataFrame:
    """One row for each method and query: the mean of its repeats."""
    means = [F.mean(c).alias(c) for c in ("pre_ms", "enum_ms", "total_ms", "driver_mb", "jvm_mb", "shuffle_mb", "spill_mb", "execution_mb")]
    return runs.groupBy("method", "query", "size").agg(*means, F.max("timed_out").alias("timed_out"), F.max("n").alias("n"))


def summary(runs: DataFrame) -> DataFrame:
    """Mean and median times, unsolved queries, median matches a second, memory, by method."""
    return per_query(runs).groupBy("method").agg(
        F.count("*").alias("queries"), F.mean("total_ms").alias("mean_total_ms"), F.expr("percentile(total_ms, 0.5)").alias("median_total_ms"),
        F.mean("pre_ms").alias("mean_pre_ms"), F.mean("enum_ms").alias("mean_enum_ms"), F.sum(F.col("timed_out").cast("int")).alias("unsolved"),
        F.expr("percentile(n / greatest(enum_ms, 1.0) * 1000, 0.5)").alias("median_matches_s"), F.mean("driver_mb").alias("mean_driver_mb"),
        F.mean("jvm_mb").alias("mean_jvm_mb"), F.mean("shuffle_mb").alias("mean_shuffle_mb"), F.max("execution_mb").alias("peak_execution_mb"),
    )


def by_size(runs: DataFrame) -> DataFrame:
    """Mean enumeration time and unsolved queries by method and query size."""
    return per_query(runs).groupBy("method", "size").agg(F.count("*").alias("queries"), F.mean("enum_ms").alias("mean_enum_ms"), F.sum(F.col("timed_out").cast("int")).alias("unsolved"))


def against_second_best(runs: DataFrame, method: str, time_of: str = "total_ms") -> DataFrame:
    """query, ours, second, speed_up: this method against the best other one on each query."""
    each = per_query(runs)
    ours = each.where(F.col("method") == method).select("query", F.col(time_of).alias("ours"))
    best = Window.partitionBy("query").orderBy(time_of, "method")
    other = each.where(F.col("method") != method).withColumn("k", F.row_number().over(best)).where("k = 1")
    return ours.join(other.select("query", F.col(time_of).alias("second"), F.col("method").alias("second_method")), "query").withColumn("speed_up", F.col("second") / F.col("ours"))


def scatter(runs: DataFrame, method: str, other: str) -> DataFrame:
    """One row: of the queries of the largest size, on which share `method` enumerates faster than `other`."""
    each = per_query(runs)
    top = each.agg(F.max("size").alias("size"))
    pair = [each.where(F.col("method") == m).join(F.broadcast(top), "size", "left_semi").select("query", F.col("enum_ms").alias(c)) for m, c in ((method, "x"), (other, "y"))]
    return pair[0].join(pair[1], "query").agg(F.count("*").alias("queries"), F.mean((F.col("x") < F.col("y")).cast("double")).alias("share_faster"))


def disagreements(runs: DataFrame) -> DataFrame:
    """Queries on which two runs that ended in time found different numbers of matches: none may."""
    return runs.where("NOT timed_out").groupBy("query").agg(F.min("n").alias("least"), F.max("n").alias("most")).where("least <> most")

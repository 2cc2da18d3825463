"""Shared plumbing: table reading, partition offsets, memory of worker processes."""

from __future__ import annotations

import pickle
from collections.abc import Callable, Iterable, Iterator
from typing import TypeVar

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema

from ..functions.scratch import drop_path, nullable, scratch_path, scratch_root, written

#: fixed value: a word is a run of anything but ASCII white space
WORD = r"[^\x20\x09-\x0D]+"


def take_over(name: str, release) -> None:
    """A worker process is used again by other operators: what they still hold goes first."""
    import gc

    others = [k for k in _HELD if k != name]
    for k in others:
        _HELD.pop(k)()
    if others:
        gc.collect()
    _HELD[name] = release


_HELD: dict = {}


def trim() -> None:
    """Gives memory that earlier fits have freed back to the system, where the C library can."""
    import ctypes
    import gc

    gc.collect()
    release = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if release is not None:
        release(0)


M = TypeVar("M")


def fitted(rows: DataFrame, fit: Callable[[pa.Table], M]) -> M:
    """What `fit` makes of a bounded sample, in one task: the driver holds the result, not what the fit needs."""
    schema = to_arrow_schema(rows.schema)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        take_over("fit", lambda: None)
        model = pickle.dumps(fit(pa.Table.from_batches(list(batches), schema)), protocol=5)
        yield pa.RecordBatch.from_pydict({"model": pa.array([model], pa.binary())})
        trim()

    got = rows.repartition(1).mapInArrow(run, "model binary").collect()  # one row
    return pickle.loads(got[0].model) if got else fit(schema.empty_table())


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def running_offsets(totals: DataFrame, keys: list[str], part: str, sums: list[str]) -> DataFrame:
    """For each (keys, part): the sum of each column over the earlier parts of the same keys.

    totals has one row for each key and partition, so a window's group is bounded by the
    number of partitions, not by rows.
    """
    from pyspark.sql import Window

    w = Window.partitionBy(*keys).orderBy(part).rowsBetween(Window.unboundedPreceding, -1)
    return totals.select(*keys, part, *[F.coalesce(F.sum(c).over(w), F.lit(0)).alias(f"{c}_before") for c in sums])


__all__ = ["WORD", "drop_path", "fitted", "nullable", "running_offsets", "scratch_path", "scratch_root", "table", "take_over", "trim", "written"]

"""Tables in the folder that driver and executors share: they cut lineage and survive lost executors."""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T


def scratch_root(spark: SparkSession) -> str:
    """Folder that driver and executors share: spark.checkpoint.dir of the session.

    Only where it is unset and one machine does all the work (a local master, as in tests) a
    temporary folder is made and removed at exit; a cluster must name its own.
    """
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        root = held.get() if held.isDefined() else None
    if not root:
        root = _OWN.get(spark.sparkContext.applicationId)
    if not root:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        root = "file://" + tempfile.mkdtemp(prefix="bundlegraph-")
        atexit.register(shutil.rmtree, root[len("file://"):], ignore_errors=True)
        _OWN[spark.sparkContext.applicationId] = root
    return root


_OWN: dict[str, str] = {}
_MADE: list[list[str]] = [[]]
#: Results of this many latest queries stay readable.
SCOPES = 8


def scratch_path(spark: SparkSession, name: str, keep: bool = False) -> str:
    """A new path; unless kept for the session, it goes when SCOPES newer queries have been made."""
    path = f"{scratch_root(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"
    if not keep:
        _MADE[-1].append(path)
    return path


def new_scope(spark: SparkSession) -> None:
    """A query begins: what queries long before it wrote is deleted."""
    _MADE.append([])
    while len(_MADE) > SCOPES:
        for path in _MADE.pop(0):
            drop_path(spark, path)


def drop_path(spark: SparkSession, path: str) -> None:
    at, fs = _filesystem(spark, path)
    fs.delete(at, True)


def path_exists(spark: SparkSession, path: str) -> bool:
    at, fs = _filesystem(spark, path)
    return fs.exists(at)


def fingerprint(spark: SparkSession, path: str) -> tuple[int, int, int]:
    """Files right below a path: how many, their bytes and the latest change."""
    at, fs = _filesystem(spark, path)
    found = list(fs.listStatus(at))
    return len(found), sum(f.getLen() for f in found), max((f.getModificationTime() for f in found), default=0)


def _filesystem(spark: SparkSession, path: str):
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return at, at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


def nullable(schema: T.StructType) -> T.StructType:
    return T.StructType([T.StructField(f.name, f.dataType, True) for f in schema])


def written(df: DataFrame, name: str, codec: str = "snappy") -> DataFrame:
    """df as a table in the shared folder."""
    path = scratch_path(df.sparkSession, name)
    df.write.option("compression", codec).parquet(path)
    return df.sparkSession.read.schema(nullable(df.schema)).parquet(path)

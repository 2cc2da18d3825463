"""A cap that stops a run: the jobs of a capped action are cancelled once its time is over."""

from __future__ import annotations

import threading
import time
import uuid
from collections.abc import Callable
from typing import TypeVar

from pyspark.sql import SparkSession

T = TypeVar("T")


def within(spark: SparkSession, seconds: float | None, action: Callable[[], T]) -> tuple[T | None, bool]:
    """(result, False), or (None, True) if the time ran out and the action's jobs were cancelled.

    The action runs in a job group of its own; later jobs of a cancelled action are cancelled as well.
    """
    if seconds is None:
        return action(), False
    sc, group = spark.sparkContext, f"capped-{uuid.uuid4().hex}"
    done, fired = threading.Event(), threading.Event()

    def watch() -> None:
        if done.wait(seconds):
            return
        fired.set()
        while not done.wait(0.2):
            sc.cancelJobGroup(group)

    before = sc.getLocalProperty("spark.jobGroup.id")
    sc.setJobGroup(group, "capped action", interruptOnCancel=True)
    began = time.time()
    guard = threading.Thread(target=watch, daemon=True)
    guard.start()
    try:
        got = action()
        return (None, True) if time.time() - began > seconds else (got, False)
    except Exception:
        if fired.is_set():
            return None, True
        raise
    finally:
        done.set()
        guard.join()
        sc.setLocalProperty("spark.jobGroup.id", before)


__all__ = ["within"]

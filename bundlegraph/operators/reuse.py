"""When partial matches share an extension: the rows that agree on what it needs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import MatchPlan


def keys_of(plan: MatchPlan, i: int, key: str = "bn") -> list[str]:
    """Columns that an extension at place i depends on: linked places, or the whole dependency set."""
    places = set(plan.back[i]) if key == "bn" else set(plan.back[i]) | plan.depends[i]
    return [f"q{j}" for j in sorted(places)]


def same_key(frontier: DataFrame, plan: MatchPlan, i: int, key: str = "bn") -> DataFrame:
    """Groups of rows that share the extension at place i: the keys and how many rows have them."""
    return frontier.groupBy(*keys_of(plan, i, key)).agg(F.count("*").alias("rows"))



def sharing(frontier: DataFrame, keys: list[str]) -> DataFrame:
    """rows, keys: how many rows a frontier has and about how many distinct keys, in one pass."""
    return frontier.agg(F.count("*").alias("rows"), F.approx_count_distinct(F.struct(*keys)).alias("keys"))

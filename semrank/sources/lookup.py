"""A lookup source that stands in for web search: facts joined to items by key."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

POLICIES = {"first": lambda: F.min_by("value", "origin"), "median": lambda: F.percentile("value", F.lit(0.5)).cast("bigint"), "max": lambda: F.max("value")}


def with_facts(items: DataFrame, facts: DataFrame, conflict: str = "max") -> DataFrame:
    """Adds ``fact``. ``facts``: key, value and, for conflict='first', origin: sources that contradict one another are
    settled before the join, so an item never doubles."""
    if conflict not in POLICIES:
        raise ValueError(f"conflict is one of {', '.join(POLICIES)}")
    one = facts.groupBy("key").agg(POLICIES[conflict]().cast("bigint").alias("fact"))
    return items.join(one, "key", "left")


def conflicts(facts: DataFrame) -> DataFrame:
    """Keys with contradictory values."""
    return facts.groupBy("key").agg(F.count_distinct("value").alias("values")).where("values > 1")

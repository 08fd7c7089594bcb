"""Measures of cost."""

from __future__ import annotations

import re
import time
from collections.abc import Callable

from pyspark.sql import DataFrame


def time3(fn: Callable[[], object], n: int = 3) -> float:
    """Mean seconds of n runs."""
    took = []
    for _ in range(n):
        t = time.time()
        fn()
        took.append(time.time() - t)
    return sum(took) / n


def plan_stats(df: DataFrame) -> dict[str, int]:
    """Counts of operators in the plan as it is before adaptive changes."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    names = {"exchanges": r"Exchange (?:hash|range)partitioning", "broadcasts": r"BroadcastExchange", "sort_merge_joins": "SortMergeJoin", "hash_joins": "BroadcastHashJoin|ShuffledHashJoin", "aggregates": "HashAggregate|SortAggregate", "windows": r"Window \[", "python": "Python|Pandas|Arrow"}
    return {k: len(re.findall(v, plan)) for k, v in names.items()}


def message_counts(messages: DataFrame, key: str) -> DataFrame:
    """One row: messages sent, and what is left of them when those to one receiver are reduced first."""
    return messages.selectExpr("count(*) AS sent", f"count(DISTINCT {key}) AS receivers")

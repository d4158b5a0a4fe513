"""What physical plans must and must not contain, and what a fit has cost."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def has_cartesian(df: DataFrame) -> bool:
    return bool(re.search("CartesianProduct|BroadcastNestedLoopJoin", plan_text(df)))


def joins(df: DataFrame) -> list[str]:
    return re.findall(r"(BroadcastHashJoin|SortMergeJoin|ShuffledHashJoin|BroadcastNestedLoopJoin|CartesianProduct)", plan_text(df))


def exchanges(df: DataFrame) -> int:
    return len(re.findall(r"\bExchange ", plan_text(df)))


def read_schema(df: DataFrame) -> list[str]:
    """Column lists that the scans read."""
    return re.findall(r"ReadSchema: (struct<[^\n]*>)", plan_text(df))


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[([^\]]*)\]", plan_text(df))

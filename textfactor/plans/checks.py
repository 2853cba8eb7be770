"""What a physical plan does: scans, exchanges and joins, for tests and for a look at a query's cost."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def physical(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def joins(df: DataFrame) -> list[str]:
    return re.findall(r"(\w*(?:Join|CartesianProduct))\b", physical(df))


def assert_no_cartesian(df: DataFrame) -> DataFrame:
    """Raise if the plan pairs all rows with all rows."""
    bad = [j for j in joins(df) if j in ("CartesianProduct", "BroadcastNestedLoopJoin")]
    if bad:
        raise AssertionError(f"the plan has {bad[0]}:\n{physical(df)}")
    return df


def exchanges(df: DataFrame) -> int:
    return len(re.findall(r"(?<!Broadcast)(?<!Reused)Exchange (?:hash|range|Single|RoundRobin)", physical(df)))


def read_columns(df: DataFrame) -> list[set[str]]:
    """The columns that each file scan reads."""
    return [set(re.findall(r"(\w+):", m)) for m in re.findall(r"ReadSchema: struct<([^>]*)>?", physical(df))]


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[([^\]]*)\]", physical(df))

"""What a physical plan does, for tests: joins, exchanges, Python, and what reaches the scan."""

from __future__ import annotations

import re
from collections import Counter

from pyspark.sql import DataFrame


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def operators(df: DataFrame) -> Counter:
    """How often each operator stands in the plan."""
    names = re.findall(r"^[\s:|+*()0-9-]*([A-Z]\w+)", plan_text(df), re.M)
    return Counter(names)


def single_partition(df: DataFrame) -> int:
    """Exchanges that bring all rows to one task."""
    return plan_text(df).count("SinglePartition")


def read_columns(df: DataFrame) -> set[str]:
    """Columns that scans read."""
    return {c.split(":")[0] for schema in re.findall(r"ReadSchema: struct<([^>]*)", plan_text(df)) for c in schema.split(",") if c}


def pushed(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[([^\]]*)\]", plan_text(df))

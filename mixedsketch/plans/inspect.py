"""What a query's physical plan does, as numbers that tests can hold."""

from __future__ import annotations

import re
from collections import Counter

from pyspark.sql import DataFrame


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def operators(df: DataFrame) -> Counter:
    """How often each physical operator stands in the plan."""
    return Counter(re.findall(r"^[\s:+|*()\d-]*([A-Z]\w+)", plan_text(df), re.MULTILINE))


def scan_columns(df: DataFrame) -> list[set[str]]:
    """Columns that each Parquet scan reads."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return [set(re.findall(r"(\w+):", m)) for m in re.findall(r"ReadSchema: struct<([^>]*)>", text)]


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[([^\]]*)\]", plan_text(df))

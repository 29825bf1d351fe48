"""Plan facts that tests and benches assert, read from the executed plan."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def physical(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def exchanges(df: DataFrame) -> int:
    """Shuffles of the plan (broadcasts not counted, reused ones once)."""
    return len(re.findall(r"(?m)^[\s:+\-*()\d|]*Exchange ", physical(df)))


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[([^\]]*)\]", physical(df))


def read_columns(df: DataFrame) -> list[str]:
    return re.findall(r"ReadSchema: struct<([^>]*)>", physical(df))


def has_cartesian(df: DataFrame) -> bool:
    return "CartesianProduct" in physical(df)

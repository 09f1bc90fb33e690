"""What a physical plan has, read from its text: exchanges, joins, pushed filters, Python stages."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def physical(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def exchanges(df: DataFrame) -> int:
    """Shuffles in the plan, broadcasts left out."""
    return len(re.findall(r"(?<!Broadcast)Exchange (?:hash|range|single|roundrobin|shufflepartitionid)", physical(df), re.IGNORECASE))


def joins(df: DataFrame) -> list[str]:
    return re.findall(r"(\w+Join)\b", physical(df))


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[([^\]]*)\]", physical(df))


def read_columns(df: DataFrame) -> list[str]:
    return re.findall(r"ReadSchema: struct<([^>]*)>", physical(df))


def codegen_spans(df: DataFrame) -> int:
    return len(set(re.findall(r"\*\((\d+)\)", physical(df))))

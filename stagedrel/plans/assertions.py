"""What a plan must and must not hold, read from its explanation."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def physical(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def read_columns(df: DataFrame) -> list[set[str]]:
    """The columns that each file scan reads."""
    return [set(re.findall(r"(\w+):", m)) for m in re.findall(r"ReadSchema: struct<(.*?)>(?:\n|$)", physical(df))]


def pushed_filters(df: DataFrame) -> str:
    return " ".join(re.findall(r"PushedFilters: \[(.*?)\]", physical(df)))


def shuffles(df: DataFrame) -> int:
    return len(re.findall(r"\bExchange (?:hash|range|Single|Round)", physical(df)))


def has_python(df: DataFrame) -> bool:
    return bool(re.search(r"ArrowEvalPython|BatchEvalPython|MapInPandas|FlatMapGroups", physical(df)))


def has_cross_join(df: DataFrame) -> bool:
    return "CartesianProduct" in physical(df)

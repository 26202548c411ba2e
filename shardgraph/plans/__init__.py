"""Reading physical plans: what tests and users check before a job goes to a large cluster."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def text(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def exchanges(df: DataFrame) -> int:
    return len(re.findall(r"\bExchange (?:hash|range|Single|Round)", text(df)))


def joins(df: DataFrame) -> list[str]:
    return re.findall(r"\b(BroadcastHashJoin|SortMergeJoin|ShuffledHashJoin|BroadcastNestedLoopJoin|CartesianProduct)\b", text(df))


def read_columns(df: DataFrame) -> list[str]:
    return [c for m in re.findall(r"ReadSchema: struct<([^>]*)>", text(df)) for c in re.findall(r"(\w+):", m)]


def pushed(df: DataFrame) -> list[str]:
    """Filters that reach the files; Spark shortens long lists, so the last one may be cut off."""
    return [x for m in re.findall(r"PushedFilters: \[([^\]]*)", text(df)) for x in re.findall(r"\w+\([^),]*", m)]


def partition_filters(df: DataFrame) -> bool:
    return bool(re.search(r"PartitionFilters: \[[^\]]+\]", text(df)))


def has_python(df: DataFrame) -> bool:
    return bool(re.search("ArrowEvalPython|BatchEvalPython|MapInArrow|MapInPandas|FlatMapGroups", text(df)))

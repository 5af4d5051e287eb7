"""Facts about a physical plan, for tests and for reading reports."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def text(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def formatted(df: DataFrame) -> str:
    return df.sparkSession.sparkContext._jvm.PythonSQLUtils.explainString(df._jdf.queryExecution(), "formatted")


def counts(df: DataFrame) -> dict[str, int]:
    """Number of exchanges, broadcasts, sorts, joins and Python nodes."""
    t = text(df)
    kinds = {
        "hash_exchange": r"Exchange hashpartitioning", "range_exchange": r"Exchange rangepartitioning", "single": r"Exchange SinglePartition", "broadcast": r"BroadcastExchange",
        "sort": r"(?<!Take)\bSort \[", "cartesian": r"CartesianProduct", "nested_loop": r"BroadcastNestedLoopJoin", "python": r"Python|Pandas|Arrow",
    }
    return {k: len(re.findall(p, t)) for k, p in kinds.items()}


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[(.*)\]", formatted(df))


def read_schemas(df: DataFrame) -> list[str]:
    return re.findall(r"ReadSchema: (struct<.*>)", formatted(df))

"""Properties of executed plans that tests assert."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def exchanges(df: DataFrame) -> int:
    return len(re.findall(r"(?<!Broadcast)Exchange (?!single)", plan_text(df)))


def python_nodes(df: DataFrame) -> list[str]:
    return re.findall(r"(BatchEvalPython|ArrowEvalPython|MapInPandas|FlatMap\w*InPandas)", plan_text(df))


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[([^\]]*)\]", plan_text(df))


def occurrences(df: DataFrame, what: str) -> int:
    return df._jdf.queryExecution().optimizedPlan().toString().count(what)

"""What a physical plan does, read from its text."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def operators_of(df: DataFrame) -> list[str]:
    """Operator names from the root down; the final plan where adaptive execution has run."""
    text = plan_text(df).split("== Initial Plan ==")[0]
    return re.findall(r"^[\s:+\-*()0-9]*([A-Z][A-Za-z]+)", text, re.M)


def shuffles(df: DataFrame) -> int:
    return sum(x == "Exchange" for x in operators_of(df))


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[([^\]]*)\]", plan_text(df))


def read_columns(df: DataFrame) -> list[str]:
    return re.findall(r"ReadSchema: struct<([^>]*)>", plan_text(df))

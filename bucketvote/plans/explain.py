"""What a plan holds, read from its text: assertions on physical choices."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def plan_text(df: DataFrame) -> str:
    """The physical plan before adaptive execution changes it."""
    return df._jdf.queryExecution().executedPlan().toString()


def plan_contains(df: DataFrame, operator: str) -> bool:
    return re.search(rf"\b{re.escape(operator)}", plan_text(df)) is not None


def exchanges(df: DataFrame) -> int:
    """Shuffles of a plan; broadcasts and reused exchanges do not count."""
    return len(re.findall(r"(?<!Reused)(?<!Broadcast)Exchange (?:hash|range|RoundRobin|Single)", plan_text(df)))

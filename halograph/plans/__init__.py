"""Checks on physical plans."""

from __future__ import annotations

from pyspark.sql import DataFrame


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def count_exchanges(df: DataFrame) -> int:
    """Shuffles of the plan as it stands, before adaptive execution changes it."""
    return sum(1 for line in plan_text(df).splitlines() if "Exchange " in line and "Broadcast" not in line and "Reused" not in line)


def assert_no_cartesian(df: DataFrame) -> None:
    if "CartesianProduct" in plan_text(df):
        raise AssertionError("the plan compares all pairs")


def pushed_filters(df: DataFrame) -> list[str]:
    return [line.split("PushedFilters: ")[1].split("]")[0] + "]" for line in plan_text(df).splitlines() if "PushedFilters: [" in line]

"""Assertions on physical plans, for tests and reviews."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def formatted(df: DataFrame) -> str:
    mode = df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted")
    return df._jdf.queryExecution().explainString(mode)


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[([^\]]*)\]", formatted(df))


def read_columns(df: DataFrame) -> list[str]:
    return re.findall(r"ReadSchema: struct<([^\n]*)>", formatted(df))


def exchanges(df: DataFrame) -> int:
    return len(re.findall(r"Exchange (?:hash|range|Single|Round)", plan_text(df)))


def assert_no_cartesian(df: DataFrame) -> None:
    assert not re.search(r"CartesianProduct|BroadcastNestedLoopJoin", plan_text(df))


def assert_no_python(df: DataFrame) -> None:
    assert not re.search(r"Python|Pandas|MapInArrow", plan_text(df))


def assert_pushed(df: DataFrame, column: str) -> None:
    assert any(column in p for p in pushed_filters(df)), pushed_filters(df)

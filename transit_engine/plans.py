"""Checks of physical plans."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def text(df: DataFrame) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def operators(df: DataFrame) -> list[str]:
    """Names of the physical operators, most deeply nested last."""
    tree = text(df).split("\n\n")[0]
    return [m[1] for m in re.finditer(r"^[\s:|*+\-]*\**\s*(?:\(\d+\)\s*)?([A-Za-z]+)", tree, re.M) if m[1] != "Physical"]


def assert_no(df: DataFrame, *names: str) -> None:
    """Fails if the plan has an operator of these names (CartesianProduct, BroadcastNestedLoopJoin, ...)."""
    found = [n for n in names if n in text(df)]
    assert not found, f"plan has {found}"


def exchanges(df: DataFrame) -> int:
    return len(re.findall(r"^\(\d+\) Exchange", text(df), re.M))


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[([^\]]+)\]", text(df))


def read_schemas(df: DataFrame) -> list[str]:
    return re.findall(r"ReadSchema: (\S+)", text(df))

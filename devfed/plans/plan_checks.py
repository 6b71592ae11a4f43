"""Checks of physical plans."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame

ROW_COLUMNS = re.compile(r"^(x\d+|z\d+|f\d+|label|features|y)$")


def plan_of(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def count_nodes(df: DataFrame, name: str) -> int:
    return len(re.findall(rf"\b{name}\b", plan_of(df)))


def assert_no_exchange(df: DataFrame) -> None:
    """A round over persisted blocks moves no rows."""
    above = plan_of(df).split("InMemoryTableScan")[0]
    if re.search(r"\bExchange\b", above):
        raise AssertionError("the plan deals rows out anew")


def assert_no_row_udf(df: DataFrame) -> None:
    if "BatchEvalPython" in plan_of(df):
        raise AssertionError("the plan runs Python row by row")


def assert_no_row_egress(df: DataFrame) -> None:
    """What leaves the clients after packing has no columns of rows."""
    found = [c for c in df.columns if ROW_COLUMNS.match(c)]
    if found:
        raise AssertionError(f"columns of rows leave their client: {found}")


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[([^\]]*)\]", plan_of(df))


def read_columns(df: DataFrame) -> list[str]:
    return re.findall(r"ReadSchema: struct<([^>]*)>", plan_of(df))

"""What a plan does, read from its text: for tests and for looking before running at scale."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[([^\]]*)\]", plan_text(df))


def read_columns(df: DataFrame) -> list[str]:
    """Columns of each file scan."""
    return re.findall(r"ReadSchema: struct<([^\n]*)>", plan_text(df))


def exchanges(df: DataFrame) -> int:
    return len(re.findall(r"^\(\d+\) Exchange", plan_text(df), re.M))


def problems(df: DataFrame) -> list[str]:
    """What does not scale: products, nested loops over more than a broadcast row, windows over one partition."""
    text, out = plan_text(df), []
    if "CartesianProduct" in text:
        out.append("a product of two tables")
    if re.search(r"Arguments: SinglePartition, ENSURE_REQUIREMENTS", text) and re.search(r"\) Window", text):
        out.append("a window over one partition")
    return out

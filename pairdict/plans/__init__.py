"""Reading plans: what a query's physical plan moves and pushes down."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def physical(df: DataFrame) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def count(df: DataFrame, node: str) -> int:
    """Operators of the plan whose name has the word given."""
    tree = physical(df).split("\n\n")[0]
    return sum(bool(re.search(rf"\b{node}\b", line)) for line in tree.splitlines())


def exchanges(df: DataFrame) -> int:
    return count(df, "Exchange")


def read_schema(df: DataFrame) -> list[str]:
    return re.findall(r"ReadSchema: struct<([^>]*)>", physical(df))


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[([^\]]*)\]", physical(df))

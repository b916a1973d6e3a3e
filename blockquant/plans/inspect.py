"""What a physical plan does, read off its tree: distinct exchanges, joins, pushed filters."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def text(df: DataFrame) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def nodes(df: DataFrame, name: str) -> int:
    """Distinct nodes of a kind: formatted plans number nodes and list each once."""
    return len(set(re.findall(rf"^\((\d+)\) {name}\b", text(df), re.M)))


def shuffles(df: DataFrame) -> int:
    return nodes(df, "Exchange")


def pushed(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[(.*?)\]", text(df))


def read_columns(df: DataFrame) -> list[str]:
    return re.findall(r"ReadSchema: struct<(.*?)>\n", text(df))

"""What a physical plan reads and shuffles, for tests of plans."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def text_of(df: DataFrame) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def columns_read(df: DataFrame) -> set[str]:
    """Columns in the scans' ReadSchema."""
    return {c for s in re.findall(r"ReadSchema: struct<(.*)>", text_of(df)) for c in re.findall(r"(\w+):", re.sub(r"<[^<>]*>", "", s))}


def pushed(df: DataFrame) -> str:
    return " ".join(re.findall(r"PushedFilters: \[(.*?)\]\n", text_of(df)))


def count(df: DataFrame, operator: str) -> int:
    """How often an operator stands in the plan tree."""
    tree = text_of(df).split("\n\n\n")[0]
    return len(re.findall(rf"\b{operator}\b", tree))

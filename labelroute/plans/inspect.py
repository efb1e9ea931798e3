"""Plan assertions and a route report."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def text(df: DataFrame) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def has(df: DataFrame, pattern: str) -> bool:
    return re.search(pattern, text(df)) is not None


def no_cartesian(df: DataFrame) -> bool:
    return not has(df, r"CartesianProduct")


def scanned_columns(df: DataFrame) -> set[str]:
    """Columns that the file scans of a plan read."""
    out: set[str] = set()
    for m in re.finditer(r"ReadSchema: struct<(.*)>", text(df)):
        out |= {c.split(":")[0] for c in re.split(r",(?![^<]*>)", m[1]) if c}
    return out


def pushed(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[([^\]]+)\]", text(df))

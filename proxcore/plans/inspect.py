"""What a plan does, for tests and for reviews before a run at scale."""

from __future__ import annotations

import re
from collections import Counter

from pyspark.sql import DataFrame


def text(df: DataFrame) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def operators(df: DataFrame) -> Counter[str]:
    """Physical operators and how often each occurs."""
    return Counter(re.findall(r"^[\s:+\-*|]*(?:\* )?([A-Z]\w+)(?: \w+)? \(\d+\)$", text(df).split("\n\n\n")[0], re.M))


def shuffles(df: DataFrame) -> int:
    return operators(df)["Exchange"]


def pushed_filters(df: DataFrame) -> list[str]:
    return [x for x in re.findall(r"PushedFilters: \[(.*?)\]", text(df)) if x]


def read_schemas(df: DataFrame) -> list[str]:
    return re.findall(r"ReadSchema: (struct<.*?>)$", text(df), re.M)


def partition_filters(df: DataFrame) -> list[str]:
    return [x for x in re.findall(r"PartitionFilters: \[(.*?)\]", text(df)) if x]


def problems(df: DataFrame) -> list[str]:
    """What shouldn't stand in a plan for large data: products, and Python where SQL would do."""
    found = operators(df)
    return [x for x in ("CartesianProduct", "BatchEvalPython") if found[x]]

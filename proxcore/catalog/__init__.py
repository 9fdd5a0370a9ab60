"""Queries over the given tables, each with the SQL that an independent engine answers it by."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from proxcore.catalog import community, relational, structure, surroundings

Query = Callable[[SparkSession, str], DataFrame]


def queries() -> dict[str, Query]:
    return structure.QUERIES | community.QUERIES | surroundings.QUERIES | relational.QUERIES


def oracle_sql() -> dict[str, str]:
    return structure.SQL | community.SQL | surroundings.SQL | relational.SQL

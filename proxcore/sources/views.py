"""Temporal graphs over the given tables, and the same in SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from proxcore.graph import SlotGraph, TemporalGraph
from proxcore.sources.tables import table


def _orders(spark: SparkSession, d: str, quarter: bool) -> DataFrame:
    o, at = table(spark, d, "orders"), F.col("o_orderdate")
    o = o.where(at < F.lit("1995-04-01").cast("timestamp_ntz")) if quarter else o
    t = F.datediff(at, F.lit("1995-01-01").cast("date")) if quarter else F.year(at) * 12 + F.month(at)
    return o.select("o_orderkey", "o_custkey", t.cast("bigint").alias("t"))


def copurchase(spark: SparkSession, d: str, quarter: bool = False) -> TemporalGraph:
    """Parts that one order has; an order has few lines, so pairs stay in proportion."""
    lines = table(spark, d, "lineitem").select("l_orderkey", "l_partkey").join(_orders(spark, d, quarter), F.col("l_orderkey") == F.col("o_orderkey")).select("o_orderkey", "l_partkey", "t")
    other = lines.select(F.col("o_orderkey").alias("k"), F.col("l_partkey").alias("v"))
    return TemporalGraph.from_edges(lines.join(other, (F.col("o_orderkey") == F.col("k")) & (F.col("l_partkey") < F.col("v"))).select(F.col("l_partkey").alias("u"), "v", "t"))


def trade(spark: SparkSession, d: str, quarter: bool = False) -> TemporalGraph:
    """Customers (even numbers) and the suppliers (odd ones) of their orders."""
    lines = table(spark, d, "lineitem").select("l_orderkey", "l_suppkey").join(_orders(spark, d, quarter), F.col("l_orderkey") == F.col("o_orderkey"))
    return TemporalGraph.from_edges(lines.select((2 * F.col("o_custkey")).alias("u"), (2 * F.col("l_suppkey") + 1).alias("v"), "t"))


def meet(spark: SparkSession, d: str, seconds: int = 3600) -> TemporalGraph:
    """Users who purchase in the same slot of time."""
    slots = table(spark, d, "events").where("event_type = 'purchase'").select(F.col("user_id").alias("v"), F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / seconds).alias("t")).distinct()
    return SlotGraph(slots)


def nations(spark: SparkSession, d: str) -> TemporalGraph:
    """Nations of customers and of their suppliers."""
    lines = table(spark, d, "lineitem").select("l_orderkey", "l_suppkey").join(_orders(spark, d, False), F.col("l_orderkey") == F.col("o_orderkey"))
    a = lines.join(table(spark, d, "customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey")).join(table(spark, d, "supplier").select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    return TemporalGraph.from_edges(a.select(F.col("c_nationkey").alias("u"), F.col("s_nationkey").alias("v"), "t"))


VIEWS: dict[str, Callable[[SparkSession, str], TemporalGraph]] = {
    "copurchase": copurchase, "copurchase_q1": lambda s, d: copurchase(s, d, True), "trade": trade, "trade_q1": lambda s, d: trade(s, d, True),
    "meet": meet, "meet10": lambda s, d: meet(s, d, 600), "nation": nations,
}

_PAIRS = "SELECT DISTINCT least(a, b) AS u, greatest(a, b) AS v, CAST(t AS BIGINT) AS t FROM ({}) WHERE a <> b"
_MONTH, _DAY, _Q1 = "year(o_orderdate) * 12 + month(o_orderdate)", "date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE))", "WHERE o_orderdate < TIMESTAMP '1995-04-01'"
_CO = "SELECT x.l_partkey AS a, y.l_partkey AS b, {} AS t FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey AND x.l_partkey < y.l_partkey JOIN orders ON o_orderkey = x.l_orderkey {}"
_TRADE = "SELECT 2 * o_custkey AS a, 2 * l_suppkey + 1 AS b, {} AS t FROM lineitem JOIN orders ON o_orderkey = l_orderkey {}"
_SLOTS = "(SELECT DISTINCT user_id, CAST(floor(epoch(ts) / {0}) AS BIGINT) AS t FROM events WHERE event_type = 'purchase')"
_MEET = f"SELECT x.user_id AS a, y.user_id AS b, x.t FROM {_SLOTS} x JOIN {_SLOTS} y ON x.t = y.t AND x.user_id < y.user_id"
#: The edges of each view in the oracle's SQL.
EDGE_SQL = {
    "copurchase": _PAIRS.format(_CO.format(_MONTH, "")), "copurchase_q1": _PAIRS.format(_CO.format(_DAY, _Q1)),
    "trade": _PAIRS.format(_TRADE.format(_MONTH, "")), "trade_q1": _PAIRS.format(_TRADE.format(_DAY, _Q1)),
    "meet": _PAIRS.format(_MEET.format(3600)), "meet10": _PAIRS.format(_MEET.format(600)),
    "nation": _PAIRS.format(f"SELECT CAST(c_nationkey AS BIGINT) AS a, CAST(s_nationkey AS BIGINT) AS b, {_MONTH} AS t FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN supplier ON s_suppkey = l_suppkey"),
}

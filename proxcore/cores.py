"""Biased degrees, core numbers, threshold cores and components, for many queries at once.

Weights are whole units (a score times UNIT, rounded), so that sums don't depend on their order. Tables of members are
(q, v); tables of weights (q, v, units); a vertex without a row weighs nothing.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from proxcore.runtime import Growing, settle

UNIT = 10**9


def in_units(prox: DataFrame, unit: int = UNIT) -> DataFrame:
    """q, v, units."""
    return prox.select("q", "v", F.round(F.col("prox") * unit).cast("bigint").alias("units")).where("units > 0")


def edge_weighted(static: DataFrame) -> DataFrame:
    """static with w, the weight of each edge; 1 where it has none."""
    return static if "w" in static.columns else static.select("v", "nbr", F.lit(1).alias("w"))


def biased_degree(static: DataFrame, weights: DataFrame, members: DataFrame | None = None) -> DataFrame:
    """q, v, rho: for each member (by default every vertex that a weighted one neighbours) the weight of its member neighbours."""
    w = weights if members is None else weights.join(members.select("q", "v"), ["q", "v"], "left_semi")
    sums = w.join(edge_weighted(static), "v").groupBy("q", F.col("nbr").alias("v")).agg(F.sum(F.col("units") * F.col("w")).alias("rho"))
    if members is None:
        return sums
    return members.select("q", "v").join(sums, ["q", "v"], "left").select("q", "v", F.coalesce("rho", F.lit(0)).cast("bigint").alias("rho"))


def threshold_core(static: DataFrame, weights: DataFrame, floor: DataFrame, members: DataFrame | None = None) -> DataFrame:
    """q, v: the unique largest set in which every biased degree reaches its query's floor (q, beta): removal in bulk."""
    now = settle((biased_degree(static, weights) if members is None else members).select("q", "v"))
    while True:
        kept = settle(biased_degree(static, weights, now).join(floor, "q").where(F.col("rho") >= F.col("beta")).select("q", "v"))
        if kept.count() == now.count():
            return kept
        now = kept


def core_numbers(static: DataFrame, weights: DataFrame, members: DataFrame | None = None, *, most_rounds: int | None = None) -> DataFrame:
    """q, v, core: the largest threshold whose core holds v; vertices of core 0 have no row.

    Estimates start as biased degrees and are lowered until nothing changes: a vertex supports the level c if its
    neighbours with estimates of at least c weigh at least c together. Only vertices with a changed neighbour are taken
    up again."""
    now = settle(biased_degree(static, weights, members).where("rho > 0").select("q", "v", F.col("rho").alias("core")))
    changed, rounds = None, 0
    order = Window.partitionBy("q", "v").orderBy(F.desc("near"), "nbr").rowsBetween(Window.unboundedPreceding, 0)
    while True:
        todo = now if changed is None else changed.join(static.select("v", "nbr"), "v").select("q", F.col("nbr").alias("v")).distinct().join(now, ["q", "v"])
        around = todo.join(edge_weighted(static), "v").join(now.select("q", F.col("v").alias("nbr"), F.col("core").alias("near")), ["q", "nbr"]).join(weights.select("q", F.col("v").alias("nbr"), "units"), ["q", "nbr"])
        level = around.withColumn("level", F.least("near", F.sum(F.col("units") * F.col("w")).over(order))).groupBy("q", "v").agg(F.max("level").alias("level"))
        lowered = settle(todo.join(level, ["q", "v"], "left").select("q", "v", F.coalesce("level", F.lit(0)).alias("level"), "core").where("level < core"))
        rounds += 1
        if lowered.limit(1).count() == 0 or rounds == most_rounds:
            return now.where("core > 0")
        now = settle(now.join(lowered.select("q", "v", "level"), ["q", "v"], "left").select("q", "v", F.coalesce("level", "core").alias("core")).where("core > 0"))
        changed = lowered.select("q", "v")


def component(static: DataFrame, members: DataFrame) -> DataFrame:
    """q, v: of each query's members those that are connected to it; by rounds of semi joins from the frontier. static: v, nbr; or
    v, t, where all who share a time meet."""
    inside = settle(members.select("q", "v"))
    seen = Growing(inside.where(F.col("v") == F.col("q")))
    frontier = seen.table
    while True:
        if "t" in static.columns:
            near = frontier.join(static, "v").select("q", "t").distinct().join(static, "t").select("q", "v").distinct()
        else:
            near = frontier.join(static.select("v", "nbr"), "v").select("q", F.col("nbr").alias("v")).distinct()
        frontier = seen.add(near.join(inside, ["q", "v"], "left_semi").join(seen.table, ["q", "v"], "left_anti"))
        if frontier.limit(1).count() == 0:
            return seen.table


def connected_components(static: DataFrame) -> DataFrame:
    """v, label (the least vertex of its component): labels spread to neighbours and then jump to their label's label."""
    now = settle(static.groupBy("v").agg(F.least(F.min("nbr"), F.first("v")).alias("label")))
    while True:
        near = static.join(now.select(F.col("v").alias("nbr"), F.col("label").alias("near")), "nbr").groupBy("v").agg(F.min("near").alias("near"))
        low = now.join(near, "v").select("v", F.col("label").alias("was"), F.least("label", "near").alias("label"))
        jump = low.join(low.select(F.col("v").alias("label"), F.col("label").alias("next")), "label").select("v", "was", F.least("label", "next").alias("label"))
        fresh = settle(jump)
        now = fresh.select("v", "label")
        if fresh.where("label <> was").limit(1).count() == 0:
            return now


def is_proximity_core(static: DataFrame, weights: DataFrame, members: DataFrame, floor: DataFrame) -> DataFrame:
    """q, holds: connected, with the query, and every biased degree reaches the floor (q, beta)."""
    low = biased_degree(static, weights, members).groupBy("q").agg(F.min("rho").alias("rho"), F.count("*").alias("n"))
    joined = component(static, members).groupBy("q").agg(F.count("*").alias("k"))
    return low.join(joined, "q", "left").join(floor, "q").select("q", ((F.col("rho") >= F.col("beta")) & (F.coalesce("k", F.lit(0)) == F.col("n"))).alias("holds"))

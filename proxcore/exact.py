"""Exact communities: the largest connected set with the query whose smallest biased degree is as large as can be."""

from __future__ import annotations

import warnings
from collections.abc import Iterable

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxcore import compact, kernels
from proxcore.cores import UNIT, biased_degree, component, core_numbers, in_units, threshold_core
from proxcore.graph import TemporalGraph
from proxcore.proximity import Queries, prepared, prox_hops, prox_multi
from proxcore.runtime import query_table, settle
from proxcore.transitions import Decay


def from_weights(static: DataFrame, weights: DataFrame, queries: DataFrame, *, method: str = "refine", most_edges: int = 1_000_000) -> DataFrame:
    """q, v, beta (units). By monotony the query's core number is the best value, and its component among vertices of at least
    that core number is the largest set that has it. A query of core number 0 gets its whole component.

    method: refine (distributed core numbers), bisect (threshold cores), or peel (one task for each query, on what is left
    after pruning, for subgraphs of at most most_edges edges)."""
    static, weights = settle(static), settle(weights)
    has = queries.join(static.select(F.col("v").alias("q")).distinct(), "q", "left_semi")
    if method == "peel":
        return peel(static, weights, has, most_edges)
    if method == "bisect":
        best = bisect(static, weights, has)
        floor = has.join(best, "q", "left").select("q", F.coalesce("beta", F.lit(0)).alias("beta"))
        inside = threshold_core(static, weights, floor.where("beta > 0"))
    else:
        cores = settle(core_numbers(static, weights))
        floor = settle(has.join(cores.select(F.col("q"), "v", "core").where("v = q").select("q", "core"), "q", "left").select("q", F.coalesce("core", F.lit(0)).alias("beta")))
        inside = cores.join(floor.where("beta > 0"), "q").where("core >= beta").select("q", "v")
    zero = floor.where("beta = 0").select("q")
    everything = zero.crossJoin(static.select("v").distinct()) if zero.limit(1).count() else inside.where("false")  # only queries that nothing near has mass
    return component(static, inside.unionByName(everything)).join(floor, "q").select("q", "v", "beta")


def bisect(static: DataFrame, weights: DataFrame, queries: DataFrame) -> DataFrame:
    """q, beta: by bisection, all queries at a time, between 0 and the query's biased degree."""
    bounds = settle(queries.join(biased_degree(static, weights).where("v = q").select("q", "rho"), "q", "left").select("q", F.lit(0).cast("bigint").alias("low"), F.coalesce("rho", F.lit(0)).alias("high")))
    while bounds.where("low < high").limit(1).count():
        mid = settle(bounds.where("low < high").select("q", F.expr("(low + high + 1) div 2").alias("beta")))
        good = threshold_core(static, weights, mid, biased_degree(static, weights).join(mid.select("q"), "q", "left_semi")).where("v = q").select("q", F.lit(True).alias("good"))
        bounds = settle(bounds.join(mid, "q", "left").join(good, "q", "left").select("q", F.when(F.col("good"), F.col("beta")).otherwise(F.col("low")).alias("low"), F.when(F.col("beta").isNotNull() & F.col("good").isNull(), F.col("beta") - 1).otherwise(F.col("high")).alias("high")))
    return bounds.select("q", F.col("low").alias("beta"))


def peel(static: DataFrame, weights: DataFrame, queries: DataFrame, most_edges: int) -> DataFrame:
    """The sequential method, a task for each query, on the query's weighted neighbourhood."""
    w = weights.join(queries, "q", "left_semi")
    near = settle(biased_degree(static, w).join(queries, "q", "left_semi").select("q", "v").unionByName(queries.select("q", F.col("q").alias("v"))).distinct())
    edges = near.join(static, "v").join(near.select("q", F.col("v").alias("nbr")), ["q", "nbr"], "left_semi").where("v < nbr")
    sized = settle(edges.join(w.select("q", "v", F.col("units").alias("a")), ["q", "v"], "left").join(w.select("q", F.col("v").alias("nbr"), F.col("units").alias("b")), ["q", "nbr"], "left").na.fill(0, ["a", "b"]))
    worst = sized.groupBy("q").count().agg(F.max("count")).first()[0] or 0
    if worst > most_edges:
        warnings.warn(f"a query's subgraph has {worst} edges, beyond the {most_edges} of a task: core numbers are refined instead, with equal results", stacklevel=2)
        return from_weights(static, weights, queries, method="refine")

    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        q = int(key[0])
        units = dict(zip(pdf["v"], pdf["a"], strict=True)) | dict(zip(pdf["nbr"], pdf["b"], strict=True))
        beta, members = kernels.exact_peel(kernels.adjacency(zip(pdf["v"], pdf["nbr"], strict=True)), units, q)
        return pd.DataFrame({"q": q, "v": sorted(members), "beta": beta})

    found = settle(sized.groupBy("q").applyInPandas(run, "q bigint, v bigint, beta bigint"))
    zero = found.where("beta = 0").select("q").distinct().unionByName(queries.join(found.select("q").distinct(), "q", "left_anti"))
    if zero.limit(1).count() == 0:
        return found
    whole = component(static, zero.crossJoin(static.select("v").distinct())).withColumn("beta", F.lit(0).cast("bigint"))
    return found.where("beta > 0").unionByName(whole)


def exact_community(g: TemporalGraph, queries: Queries, alpha: float = 0.2, *, decay: Decay = "reciprocal", unit: int = UNIT, method: str = "auto") -> DataFrame:
    """q, v, beta. A query without edges has no community.

    method: those of from_weights, task (blocks of queries with the whole graph, `compact`), or auto: task for graphs that
    fit, refine beyond."""
    if method == "task" or method == "auto" and compact.fits(g, queries):
        return compact.exact(g, queries, alpha, decay=decay, unit=unit)
    method = "refine" if method == "auto" else method
    g, states = prepared(g, decay)
    q = settle(query_table(g.edges.sparkSession, queries))
    weights = settle(in_units(prox_hops(g, q, alpha, decay=decay, states=states), unit))
    return from_weights(g.static, weights, q, method=method).select("q", "v", (F.col("beta") / unit).alias("beta"))


def exact_community_multi(g: TemporalGraph, queries: Iterable[int], alpha: float = 0.2, *, combine: str = "mean", unit: int = UNIT) -> DataFrame:
    """v, beta for a set of query vertices: scores are combined; the level is the largest at which one component of the
    threshold core holds them all. No rows if no component does."""
    wanted = sorted(set(queries))
    g, states = prepared(g)
    spark = g.edges.sparkSession
    static = settle(g.static)
    head = wanted[0]
    per_query = settle(prox_hops(g, wanted, alpha, states=states))
    weights = settle(in_units(prox_multi(per_query, combine).select(F.lit(head).cast("bigint").alias("q"), "v", "prox"), unit))
    cores = settle(core_numbers(static, weights))
    levels = [r[0] for r in cores.join(query_table(spark, wanted).withColumnRenamed("q", "v"), "v").select("core").collect()]  # one for each query vertex
    high = min(levels) if len(levels) == len(wanted) else 0
    choices = settle(cores.where(F.col("core") > 0).select("core").distinct())

    def holds(beta: int) -> DataFrame | None:
        inside = cores.where(F.col("core") >= beta).select("q", "v") if beta else static.select(F.lit(head).cast("bigint").alias("q"), "v").distinct()
        found = component(static, inside)
        return found if found.where(F.col("v").isin(wanted)).count() == len(wanted) else None

    best, beta = None, 0
    while True:  # bisection over the distinct levels that are left, above beta and up to high
        mid = choices.where((F.col("core") > beta) & (F.col("core") <= high)).agg(F.percentile_approx("core", 0.5, 1000)).first()[0]
        if mid is None:
            break
        if (found := holds(mid)) is not None:
            best, beta = found, mid
        else:
            high = mid - 1
    best = best if best is not None else holds(0)
    if best is None:
        return spark.createDataFrame([], "v bigint, beta double")
    return best.select("v", F.lit(beta / unit).alias("beta"))



"""Baselines on the graph without times: cores, trusses, sweep cuts, the floor k-core, and the choice from detected sets."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from proxcore import compact
from proxcore.cores import component, core_numbers
from proxcore.graph import TemporalGraph
from proxcore.proximity import Queries, prepared, prox_hops, push_static
from proxcore.runtime import Growing, query_table, settle


def _at_own_level(static: DataFrame, levels: DataFrame, queries: DataFrame) -> DataFrame:
    """q, v, k: each query's component among vertices of at least its level, from levels (v, k) that all queries share."""
    own = queries.join(levels.select(F.col("v").alias("q"), F.col("k").alias("level")), "q")
    inside = settle(own.join(levels, F.col("k") >= F.col("level")).select("q", "v", "level"))  # a row for each query and member
    return component(static, inside).join(own, "q").select("q", "v", F.col("level").alias("k"))


def static_core(g: TemporalGraph, queries: Queries, weight: str = "static", *, method: str = "auto") -> DataFrame:
    """q, v, k: the component of the core of the largest k that holds the query. weight="temporal" counts temporal edges.
    method: refine (distributed), task (`compact`), or auto: task for graphs that fit."""
    if method == "task" or method == "auto" and compact.fits(g, queries, by_slots=False):
        return compact.core(g, queries, temporal=weight == "temporal")
    static = g.static if weight == "static" else g.arcs.groupBy(F.col("src").alias("v"), F.col("dst").alias("nbr")).agg(F.count("*").alias("w"))
    static = settle(static)
    ones = static.select(F.lit(0).cast("bigint").alias("q"), "v", F.lit(1).cast("bigint").alias("units")).distinct()
    levels = settle(core_numbers(static, ones).select("v", F.col("core").alias("k")))
    return _at_own_level(static, levels, query_table(g.edges.sparkSession, queries))


def triangles(static: DataFrame) -> DataFrame:
    """a, b, c: each triangle once. Edges lead to the end of higher degree, so a vertex has few of them."""
    degree = static.groupBy("v").agg(F.count("*").alias("d"))
    ranked = static.where("v < nbr").join(degree, "v").join(degree.select(F.col("v").alias("nbr"), F.col("d").alias("e")), "nbr")
    up = (F.col("d") < F.col("e")) | ((F.col("d") == F.col("e")) & (F.col("v") < F.col("nbr")))
    out = settle(ranked.select(F.when(up, F.col("v")).otherwise(F.col("nbr")).alias("low"), F.when(up, F.col("nbr")).otherwise(F.col("v")).alias("high")))
    pairs = out.join(out.select("low", F.col("high").alias("other")), "low").where("high < other")
    closed = pairs.join(static.select(F.col("v").alias("high"), F.col("nbr").alias("other")), ["high", "other"])
    s = F.array_sort(F.array("low", "high", "other"))
    return closed.select(s[0].alias("a"), s[1].alias("b"), s[2].alias("c"))


def truss_numbers(static: DataFrame) -> DataFrame:
    """u, v, k for u < v: the largest k such that the edge is in a k-truss; by lowering estimates from the support."""
    t = settle(triangles(static))
    side = lambda x, y, p, r, s, w: t.select(F.col(x).alias("u"), F.col(y).alias("v"), F.struct(F.col(p).alias("u"), F.col(r).alias("v")).alias("e"), F.struct(F.col(s).alias("u"), F.col(w).alias("v")).alias("f"))
    around = settle(side("a", "b", "a", "c", "b", "c").unionByName(side("a", "c", "a", "b", "b", "c")).unionByName(side("b", "c", "a", "b", "a", "c")))
    now = settle(around.groupBy("u", "v").agg(F.count("*").alias("k")))
    order = Window.partitionBy("u", "v").orderBy(F.desc("near"))
    changed = None
    while True:
        of = lambda name: now.select(F.struct("u", "v").alias(name), F.col("k").alias(f"k_{name}"))  # noqa: E731, B023
        # only edges that share a triangle with a lowered one are taken up again
        todo = now if changed is None else around.join(changed, "e", "left_semi").select("u", "v").unionByName(around.join(changed.withColumnRenamed("e", "f"), "f", "left_semi").select("u", "v")).distinct().join(now, ["u", "v"])
        near = around.join(todo.select("u", "v"), ["u", "v"], "left_semi").join(of("e"), "e").join(of("f"), "f").select("u", "v", F.least("k_e", "k_f").alias("near"))
        level = near.withColumn("level", F.least("near", F.row_number().over(order))).groupBy("u", "v").agg(F.max("level").alias("level"))
        fresh = settle(todo.join(level, ["u", "v"]).select("u", "v", F.col("level").cast("bigint").alias("lower"), "k").where("lower < k").select("u", "v", "lower"))
        if fresh.limit(1).count() == 0:
            break
        now = settle(now.join(fresh, ["u", "v"], "left").select("u", "v", F.coalesce("lower", "k").alias("k")))
        changed = fresh.select(F.struct("u", "v").alias("e"))
    rest = static.where("v < nbr").select(F.col("v").alias("u"), F.col("nbr").alias("v"))
    return rest.join(now, ["u", "v"], "left").select("u", "v", (F.coalesce("k", F.lit(0)) + 2).alias("k"))


def truss_community(g: TemporalGraph, queries: Queries) -> DataFrame:
    """q, v, k: vertices of the edges that triangles of the k-truss join to the query's, for its largest k. An edge in no
    triangle is a 2-truss by itself."""
    static = settle(g.static)
    edges = settle(truss_numbers(static))
    t = settle(triangles(static))
    q = query_table(g.edges.sparkSession, queries)
    ends = edges.select(F.col("u").alias("q"), "u", "v", "k").unionByName(edges.select(F.col("v").alias("q"), "u", "v", "k"))
    own = ends.join(q, "q")
    level = settle(own.groupBy("q").agg(F.max("k").alias("level")))
    seen = settle(own.join(level, "q").where("k = level").select("q", "u", "v"))
    e = lambda x, y: edges.select(F.col("u").alias(x), F.col("v").alias(y), F.col("k").alias(f"k_{x}{y}"))
    full = settle(t.join(e("a", "b"), ["a", "b"]).join(e("a", "c"), ["a", "c"]).join(e("b", "c"), ["b", "c"]).select("a", "b", "c", F.least("k_ab", "k_ac", "k_bc").alias("k")))
    pair = lambda x, y: F.struct(F.col(x).alias("u"), F.col(y).alias("v"))
    sides = settle(full.select("k", F.explode(F.array(pair("a", "b"), pair("a", "c"), pair("b", "c"))).alias("from"), F.array(pair("a", "b"), pair("a", "c"), pair("b", "c")).alias("all")))
    seen = Growing(seen)
    frontier = seen.table
    while True:
        step = frontier.join(level, "q").join(sides.select(F.col("from.u").alias("u"), F.col("from.v").alias("v"), "k", "all"), ["u", "v"]).where("k >= level").select("q", F.explode("all").alias("e")).select("q", "e.u", "e.v").distinct()
        frontier = seen.add(step.join(seen.table, ["q", "u", "v"], "left_anti"))
        if frontier.limit(1).count() == 0:
            break
    return seen.table.select("q", F.explode(F.array("u", "v")).alias("v")).distinct().join(level, "q").select("q", "v", F.col("level").alias("k"))


def sweep_cut(g: TemporalGraph, queries: Queries, alpha: float = 0.2, least: float = 1e-4) -> DataFrame:
    """q, v, conductance: of the prefixes by approximate score over degree, the one of the least conductance with the query."""
    static = settle(g.static)
    degree = static.groupBy("v").agg(F.count("*").alias("d"))
    score = push_static(g, queries, alpha, least=least).where("reserve > 0").join(degree, "v")
    ranked = settle(score.withColumn("r", F.row_number().over(Window.partitionBy("q").orderBy(F.desc(F.round(F.col("reserve") / F.col("d"), 12)), "v"))).select("q", "v", "d", "r"))
    inner = ranked.join(static, "v").join(ranked.select("q", F.col("v").alias("nbr"), F.col("r").alias("s")), ["q", "nbr"]).where("s < r").groupBy("q", "r").agg(F.count("*").alias("closed"))
    run = Window.partitionBy("q").orderBy("r")
    steps = ranked.join(inner, ["q", "r"], "left").withColumn("volume", F.sum("d").over(run)).withColumn("cut", F.col("volume") - 2 * F.sum(F.coalesce("closed", F.lit(0))).over(run))
    whole = static.agg(F.count("*").alias("total"))
    place = ranked.where("v = q").select("q", F.col("r").alias("own"))
    scored = steps.crossJoin(F.broadcast(whole)).join(place, "q").where("r >= own").select("q", "r", F.expr("try_divide(cut * 1.0D, least(volume, total - volume))").alias("conductance"))
    best = scored.where("conductance is not null").groupBy("q").agg(F.min_by(F.struct("r", "conductance"), F.struct("conductance", "r")).alias("b"))
    return ranked.join(best, "q").where("r <= b.r").select("q", "v", "b.conductance")


def floor_levels(static: DataFrame, prox: DataFrame, k: int) -> DataFrame:
    """q, v, level: the largest floor such that v is in the k-core of vertices with at least that proximity; none without one."""
    now = settle(prox.where("prox > 0").select("q", "v", F.col("prox").alias("level")))
    order = Window.partitionBy("q", "v").orderBy(F.desc("near"), "nbr")
    while True:
        near = now.select("q", "v").join(static, "v").join(now.select("q", F.col("v").alias("nbr"), F.col("level").alias("near")), ["q", "nbr"])
        kth = near.withColumn("r", F.row_number().over(order)).where(F.col("r") == k).select("q", "v", "near")
        fresh = settle(now.join(kth, ["q", "v"], "left").select("q", "v", F.least("level", "near").alias("level"), (F.col("near").isNull() | (F.col("near") < F.col("level"))).alias("fell"), F.col("near").isNotNull().alias("stays")))
        now = fresh.where("stays").select("q", "v", "level")
        if fresh.where("fell").limit(1).count() == 0:
            return now


def floor_kcore(g: TemporalGraph, queries: Queries, alpha: float = 0.2, k: int = 3, prox: DataFrame | None = None, *, method: str = "auto") -> DataFrame:
    """q, v, floor: the connected k-core with the query whose smallest proximity is largest. A query that no k-core of positive
    proximities holds gets its component of the plain k-core at floor 0, if it is in one. method: levels (distributed, and where prox is given),
    task (`compact`; of a larger graph the queries' components, levels where these are too large), or auto: task for graphs that fit."""
    if method == "task" or method == "auto" and prox is None and compact.fits(g, queries, by_slots=False):
        if (found := compact.or_distributed(lambda: compact.floor_kcore(g, queries, alpha, k))) is not None:
            return found
    if prox is None:
        g, states = prepared(g)
        prox = settle(prox_hops(g, queries, alpha, states=states))
    static = settle(g.static)
    q = query_table(g.edges.sparkSession, queries)
    levels = settle(floor_levels(static, prox, k))
    own = settle(q.join(levels.where("v = q").select("q", F.col("level").alias("floor")), "q", "left"))
    inside = levels.join(own.where("floor is not null"), "q").where("level >= floor").select("q", "v")
    out = component(static, inside).join(own, "q").select("q", "v", "floor")
    missing = own.where("floor is null").select("q")
    if missing.limit(1).count() == 0:
        return out
    ones = static.select(F.lit(0).cast("bigint").alias("q"), "v", F.lit(1).cast("bigint").alias("units")).distinct()
    plain = core_numbers(static, ones).where(F.col("core") >= k).select("v")
    return out.unionByName(component(static, missing.crossJoin(F.broadcast(plain))).select("q", "v", F.lit(0.0).alias("floor")))


def select_containing(found: DataFrame, queries: DataFrame) -> DataFrame:
    """q, v, score: of detected sets (set_id, v, score) with the query, the one of the best score, the least id at ties."""
    hit = found.join(queries.select("q"), F.col("v") == F.col("q")).groupBy("q").agg(F.max_by(F.struct("set_id", "score"), F.struct("score", -F.col("set_id"))).alias("b"))
    return hit.select("q", "b.set_id").join(found, "set_id").select("q", "v", "score")

"""Temporal baselines over windows: interval-AND cores, persistent cores and density bursts. Windows are batch keys, so that
all of them are worked on at a time."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxcore.cores import component, core_numbers
from proxcore.graph import TemporalGraph
from proxcore.proximity import Queries
from proxcore.runtime import Growing, query_table, settle


def in_windows(g: TemporalGraph, length: int) -> DataFrame:
    """w, u, v, t: each edge in the windows [w, w + length) that start at a time of the graph."""
    starts = g.edges.select(F.col("t").alias("w")).distinct()
    spread = g.edges.select("u", "v", "t", F.explode(F.sequence(F.col("t") - length + 1, "t")).alias("w"))
    return spread.join(starts, "w", "left_semi").select("w", "u", "v", "t")


def _both(pairs: DataFrame) -> DataFrame:
    return pairs.select("w", F.explode(F.array(F.struct(F.col("u").alias("v"), F.col("v").alias("nbr")), F.struct(F.col("v"), F.col("u").alias("nbr")))).alias("e")).select("w", "e.v", "e.nbr")


def _keyed_cores(pairs: DataFrame) -> DataFrame:
    """w, v, core: core numbers within each window's pairs (w, u, v); a vertex is named by window and vertex."""
    static = settle(_both(pairs).select(F.struct("w", "v").alias("v"), F.struct("w", F.col("nbr").alias("v")).alias("nbr")))
    ones = static.select(F.lit(0).cast("bigint").alias("q"), "v", F.lit(1).cast("bigint").alias("units")).distinct()
    return core_numbers(static, ones).select("v.w", "v.v", "core")


def interval_core(g: TemporalGraph, queries: Queries, interval: tuple[int, int]) -> DataFrame:
    """q, v, k: the core of the largest k with the query among pairs that meet at every time of [start, end]."""
    start, end = interval
    pairs = g.slice(start, end + 1).edges.groupBy("u", "v").agg(F.count_distinct("t").alias("n")).where(F.col("n") == end - start + 1).select(F.lit(start).alias("w"), "u", "v")
    return _best_windows(g, queries, pairs).select("q", "v", "k")


def best_interval(g: TemporalGraph, queries: Queries, length: int) -> DataFrame:
    """q, v, k, start: the best of all intervals of a length."""
    pairs = in_windows(g, length).groupBy("w", "u", "v").agg(F.count_distinct("t").alias("n")).where(F.col("n") == length).select("w", "u", "v")
    return _best_windows(g, queries, pairs)


def interval_core_multi(g: TemporalGraph, queries: Iterable[int], interval: tuple[int, int]) -> DataFrame:
    """v, k for a set of query vertices: the core of the largest k among pairs that meet at every time of [start, end], one
    component of which holds the set. No rows without one."""
    start, end = interval
    wanted = sorted(set(queries))
    pairs = settle(g.slice(start, end + 1).edges.groupBy("u", "v").agg(F.count_distinct("t").alias("n")).where(F.col("n") == end - start + 1).select(F.lit(0).cast("bigint").alias("w"), "u", "v"))
    levels = settle(_keyed_cores(pairs).select(F.lit(wanted[0]).cast("bigint").alias("q"), "v", "core"))
    static = settle(_both(pairs).select("v", "nbr"))
    own = [r["core"] for r in levels.where(F.col("v").isin(wanted)).collect()]  # one for each query vertex
    best, low, high = None, 0, min(own) if len(own) == len(wanted) else 0
    while low < high:  # cores are nested
        mid = (low + high + 1) // 2
        found = settle(component(static, levels.where(F.col("core") >= mid).select("q", "v")))
        if found.where(F.col("v").isin(wanted)).count() == len(wanted):
            best, low = found.select("v", F.lit(mid).cast("bigint").alias("k")), mid
        else:
            high = mid - 1
    return g.edges.sparkSession.createDataFrame([], "v bigint, k bigint") if best is None else best


def _best_windows(g: TemporalGraph, queries: Queries, pairs: DataFrame) -> DataFrame:
    pairs = settle(pairs)
    cores = settle(_keyed_cores(pairs))
    q = query_table(g.edges.sparkSession, queries)
    own = settle(cores.join(q, F.col("v") == F.col("q")).groupBy("q").agg(F.max_by(F.struct("w", "core"), F.struct("core", -F.col("w"))).alias("b")).select("q", "b.w", F.col("b.core").alias("k")))
    inside = settle(own.join(cores, "w").where("core >= k").select("q", "w", "v"))
    arcs = _both(pairs).join(own, "w").select("q", "v", "nbr")
    return _component_in(inside.select("q", "v"), arcs).join(own, "q").select("q", "v", "k", F.col("w").alias("start"))


def _component_in(members: DataFrame, arcs: DataFrame) -> DataFrame:
    """q, v: members that the query's own arcs (q, v, nbr) join to it."""
    arcs = settle(arcs)
    seen = Growing(members.where("v = q"))
    frontier = seen.table
    while True:
        near = frontier.join(arcs, ["q", "v"]).select("q", F.col("nbr").alias("v")).distinct()
        frontier = seen.add(near.join(members, ["q", "v"], "left_semi").join(seen.table, ["q", "v"], "left_anti"))
        if frontier.limit(1).count() == 0:
            return seen.table


def persistent_degree(g: TemporalGraph, theta: int) -> DataFrame:
    """w, v, degree: distinct neighbours in each window of theta times."""
    return _both(in_windows(g, theta).select("w", "u", "v").distinct()).groupBy("w", "v").agg(F.count("*").alias("degree"))


def persistent_core(g: TemporalGraph, queries: Queries, theta: int = 3, tau: int = 2, k: int = 2) -> DataFrame:
    """q, v, exact (false): the query's component of the largest set whose members each have k neighbours inside in tau windows
    of theta times at least. It holds every persistent core; the largest one itself is hard to find."""
    if g.slots is not None:
        return _persistent_by_slots(g, queries, theta, tau, k)
    arcs = settle(_both(in_windows(g, theta).select("w", "u", "v").distinct()))
    now = settle(arcs.select("v").distinct())
    while True:
        inside = arcs.join(now, "v", "left_semi").join(now.select(F.col("v").alias("nbr")), "nbr", "left_semi")
        good = inside.groupBy("w", "v").agg(F.count("*").alias("d")).where(F.col("d") >= k).groupBy("v").agg(F.count("*").alias("n"))
        fresh = settle(good.where(F.col("n") >= tau).select("v"))
        if fresh.count() == now.count():
            break
        now = fresh
    q = query_table(g.edges.sparkSession, queries).join(now.select(F.col("v").alias("q")), "q", "left_semi")
    return component(settle(g.static), q.crossJoin(now)).withColumn("exact", F.lit(False))


def _persistent_by_slots(g: TemporalGraph, queries: Queries, theta: int, tau: int, k: int) -> DataFrame:
    """The same where all who share a time meet. In a window a member is known by the set of times it is there at; two meet if their
    sets do, so degrees follow from the counts of the sets, and no pair of members is made."""
    met = g.occurrences.select("v", "t")
    starts = met.select(F.col("t").alias("w")).distinct()
    spread = met.select("v", "t", F.explode(F.sequence(F.col("t") - theta + 1, "t")).alias("w")).join(starts, "w", "left_semi")
    there = settle(spread.groupBy("w", "v").agg(F.array_sort(F.collect_set(F.col("t") - F.col("w"))).alias("at")))
    now = settle(met.select("v").distinct())
    while True:
        inside = there.join(now, "v", "left_semi")
        sets = settle(inside.groupBy("w", "at").agg(F.count("*").alias("n")))
        other = sets.select("w", F.col("at").alias("with"), "n")
        degree = sets.select("w", "at").join(other, "w").where(F.arrays_overlap("at", "with")).groupBy("w", "at").agg((F.sum("n") - 1).alias("d"))  # but itself
        good = inside.join(degree.where(F.col("d") >= k), ["w", "at"], "left_semi").groupBy("v").agg(F.count("*").alias("n"))
        fresh = settle(good.where(F.col("n") >= tau).select("v"))
        if fresh.count() == now.count():
            break
        now = fresh
    q = query_table(g.spark, queries).join(now.select(F.col("v").alias("q")), "q", "left_semi")
    return component(g.slots, q.crossJoin(now)).withColumn("exact", F.lit(False))


def density_bursts(g: TemporalGraph, length: int, slack: float = 0.1) -> DataFrame:
    """set_id (window), v, score, exact (false): for each window the densest set by removal in bulk, within 2 (1 + slack) of the
    best; the score is inner temporal edges over size times the window's times."""
    e = settle(in_windows(g, length).groupBy("w", "u", "v").agg(F.count("*").alias("m")))
    times = settle(in_windows(g, length).groupBy("w").agg(F.count_distinct("t").alias("times")))
    both = settle(e.select("w", F.explode(F.array(F.struct(F.col("u").alias("v"), F.col("v").alias("nbr")), F.struct(F.col("v"), F.col("u").alias("nbr")))).alias("e"), "m").select("w", "e.v", "e.nbr", "m"))
    now = settle(both.select("w", "v").distinct())
    history, i = None, 0
    while True:
        degree = settle(both.join(now, ["w", "v"], "left_semi").join(now.select("w", F.col("v").alias("nbr")), ["w", "nbr"], "left_semi").groupBy("w", "v").agg(F.sum("m").alias("d")))
        whole = now.join(degree, ["w", "v"], "left").na.fill(0, ["d"])
        dens = settle(whole.groupBy("w").agg((F.sum("d") / 2 / F.count("*")).alias("density")))
        step = whole.join(dens, "w").select("w", F.lit(i).alias("round"), "v", "d", "density")
        rows = step.select("w", "round", "v", "density")
        if history is None:
            history = Growing(rows)
        else:
            history.add(rows)
        now = settle(step.where(F.col("d") > 2 * (1 + slack) * F.col("density")).select("w", "v"))
        i += 1
        if now.limit(1).count() == 0:
            break
    history = history.table
    best = history.groupBy("w").agg(F.max_by("round", F.struct("density", -F.col("round"))).alias("round"))
    return history.join(best, ["w", "round"]).join(times, "w").select(F.col("w").alias("set_id"), "v", (F.col("density") / F.col("times")).alias("score"), F.lit(False).alias("exact"))


def density_burst(g: TemporalGraph, queries: Queries, max_len: int = 3) -> DataFrame:
    """q, v, score: of the bursts of windows up to max_len, the best one with the query."""
    from proxcore.baselines.static import select_containing

    found = None
    for length in range(1, max_len + 1):
        part = density_bursts(g, length).select((F.col("set_id") * max_len + (length - 1)).alias("set_id"), "v", "score")
        found = part if found is None else found.unionByName(part)
    return select_containing(settle(found), query_table(g.edges.sparkSession, queries))

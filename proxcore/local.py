"""Approximate communities: local expansion with bounds, then shrinking to a certified ratio.

The expansion takes a whole queue at a time (levels), for all queries at once. Each level pushes the residues of the arcs that
leave the queue's vertices, raises the best value seen, admits neighbours that the bounds allow, and tests whether to stop.
All bounds hold at any moment, so the order of pushes doesn't matter. A dangling arc banks its whole residue.
"""

from __future__ import annotations

import math
import uuid
from collections.abc import Iterable

import pandas as pd
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxcore import compact, kernels
from proxcore.cores import component
from proxcore.graph import TemporalGraph
from proxcore.proximity import Queries, fold, prepared, seeds
from proxcore.runtime import Growing, query_table, settle
from proxcore.transitions import Decay

#: Temporal edges that one task may hold, and that may be broadcast.
IN_TASK = 500_000


def _lower_degree(static: DataFrame, members: DataFrame, lower: DataFrame) -> DataFrame:
    """q, v, low: for each member the lower bounds of its member neighbours."""
    own = lower.join(members.select("q", "v"), ["q", "v"], "left_semi").join(static, "v").groupBy("q", F.col("nbr").alias("v")).agg(F.sum("low").alias("low"))
    return members.select("q", "v").join(own, ["q", "v"], "left").select("q", "v", F.coalesce("low", F.lit(0.0)).alias("low"))


def push(residue: DataFrame, hot: DataFrame, g: TemporalGraph, states: DataFrame, alpha: float, decay: Decay, least: float) -> tuple[DataFrame, DataFrame]:
    """Residues (q, src, dst, t, r) and banked mass (q, v, low) after the arcs that leave the hot vertices (q, v) are pushed
    where they hold at least `least`."""
    marked = settle(residue.join(hot.select("q", F.col("v").alias("src"), F.lit(True).alias("hot")), ["q", "src"], "left").withColumn("hot", F.coalesce("hot", F.lit(False)) & (F.col("r") >= least)))
    active = marked.where("hot").groupBy("q", F.col("dst").alias("v"), "t").agg(F.sum("r").alias("mass")).join(states.select("v", "t", "dangling"), ["v", "t"])
    banked = active.groupBy("q", "v").agg(F.sum(F.when(F.col("dangling"), F.col("mass")).otherwise(alpha * F.col("mass"))).alias("low"))
    flow = fold(active.where("not dangling").select("q", "v", "t", "mass"), states, g, alpha, decay)
    sent = flow.join(g.arcs, (F.col("u") == F.col("src")) & (F.col("t2") == F.col("t"))).select("q", "src", "dst", "t", F.col("flow").alias("r"))
    rest = marked.where("not hot").select("q", "src", "dst", "t", "r").unionByName(sent).groupBy("q", "src", "dst", "t").agg(F.sum("r").alias("r"))
    return settle(rest), settle(banked)


def push_temporal(g: TemporalGraph, queries: Queries, alpha: float = 0.2, *, least: float | None = None, decay: Decay = "reciprocal", most_rounds: int = 1000) -> tuple[DataFrame, DataFrame]:
    """reserve (q, v, low) and residue (q, src, dst, t, r) when no arc holds `least` (1 / m by default) any more."""
    g, states = prepared(g, decay)
    least = 1 / max(1, g.edges.count()) if least is None else least
    residue = settle(seeds(g, query_table(g.edges.sparkSession, queries)).withColumnRenamed("mass", "r"))
    lower = residue.where("false").select("q", F.col("dst").alias("v"), F.col("r").alias("low"))
    for _ in range(most_rounds):
        hot = settle(residue.where(F.col("r") >= least).select("q", F.col("src").alias("v")).distinct())
        if hot.limit(1).count() == 0:
            break
        residue, banked = push(residue, hot, g, states, alpha, decay, least)
        lower = settle(lower.unionByName(banked).groupBy("q", "v").agg(F.sum("low").alias("low")))
    return lower, residue


def _holding(static: DataFrame, members: DataFrame, wanted: DataFrame) -> DataFrame:
    """q: those whose members join all its wanted vertices (q, v); the least of them names the query."""
    hit = component(static, members).join(wanted, ["q", "v"], "left_semi").groupBy("q").agg(F.count("*").alias("n"))
    return hit.join(wanted.groupBy("q").agg(F.count("*").alias("all")), "q").where("n = all").select("q")


def expand_levels(g: TemporalGraph, queries: Queries, alpha: float = 0.2, *, decay: Decay = "reciprocal", prune: bool = True, stop: bool = True, least: float | None = None, together: DataFrame | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """members (q, v); lower (q, v, low); facts (q, residue, beta, levels, visited, reason).

    together: start residues (q, src, dst, t, r) of sets of query vertices, each under the name of its least vertex, in place of
    queries. The walk is linear in its start, so a set's bounds hold as one query's do; a best value counts only once the
    expanded vertices join all of the set, for only then they are a community of it."""
    g, states = prepared(g, decay)
    static = settle(g.static)
    spark = g.edges.sparkSession
    least = 1 / max(1, g.edges.count()) if least is None else least
    residue = settle(seeds(g, query_table(spark, queries)).withColumnRenamed("mass", "r") if together is None else together)
    queue = settle(residue.select("q", F.col("src").alias("v")).distinct())
    wanted, whole, joined = queue, queue.select("q").distinct(), False
    members, seen = queue.where("false"), Growing(queue)
    lower = queue.withColumn("low", F.lit(0.0)).where("false")
    facts = settle(whole.select("q", F.lit(1.0).alias("residue"), F.lit(0.0).alias("beta"), F.lit(0).alias("levels"), F.lit("exhausted").alias("reason")))
    level = 0
    while queue.limit(1).count():
        level += 1
        members = settle(members.unionByName(queue))
        residue, banked = push(residue, queue, g, states, alpha, decay, least)
        lower = settle(lower.unionByName(banked).groupBy("q", "v").agg(F.sum("low").alias("low")))
        if together is not None and not joined:
            whole = settle(_holding(static, members, wanted))
            joined = whole.count() == wanted.select("q").distinct().count()  # members only grow
        best = _lower_degree(static, members.join(queue.select("q").distinct(), "q", "left_semi"), lower).groupBy("q").agg(F.min("low").alias("now"))
        best = best.join(whole.withColumn("valid", F.lit(True)), "q", "left").select("q", F.when(F.col("valid"), F.col("now")).otherwise(0.0).alias("now"))
        left = residue.groupBy("q").agg(F.sum("r").alias("left"))
        facts = settle(facts.join(best, "q", "left").join(left, "q", "left").select("q", F.when(F.col("now").isNull(), F.col("residue")).otherwise(F.coalesce("left", F.lit(0.0))).alias("residue"), F.greatest("beta", F.coalesce("now", F.lit(0.0))).alias("beta"), F.when(F.col("now").isNull(), F.col("levels")).otherwise(level).alias("levels"), "reason"))
        fresh = seen.add(queue.join(static, "v").select("q", F.col("nbr").alias("v")).distinct().join(seen.table, ["q", "v"], "left_anti"))
        bound = fresh.join(static, "v").join(lower.select("q", F.col("v").alias("nbr"), "low"), ["q", "nbr"], "left").groupBy("q", "v").agg(F.coalesce(F.sum("low"), F.lit(0.0)).alias("low"))
        admitted = bound.join(facts.select("q", "residue", "beta"), "q")
        queue = settle((admitted.where(F.col("residue") + F.col("low") >= F.col("beta")) if prune else admitted).select("q", "v"))
        if stop:
            near = queue.join(lower, ["q", "v"], "left").groupBy("q").agg(F.sum(F.coalesce("low", F.lit(0.0))).alias("near"))
            ended = settle(near.join(facts, "q").where(F.col("residue") + F.col("near") < F.col("beta")).select("q"))
            members = settle(members.unionByName(queue.join(ended, "q", "left_semi")))
            facts = settle(facts.join(ended.withColumn("end", F.lit(True)), "q", "left").withColumn("reason", F.when(F.col("end"), F.lit("bound")).otherwise(F.col("reason"))).drop("end"))
            queue = settle(queue.join(ended, "q", "left_anti"))
    counts = seen.table.groupBy("q").agg(F.count("*").alias("visited"))
    return members, lower, settle(facts.join(counts, "q"))


def rho_bounds(static: DataFrame, members: DataFrame, lower: DataFrame, facts: DataFrame) -> DataFrame:
    """q, v, low, high: what the biased degree of each member lies between."""
    return _lower_degree(static, members, lower).join(facts.select("q", "residue"), "q").select("q", "v", "low", (F.col("low") + F.col("residue")).alias("high"))


def shrink_levels(static: DataFrame, members: DataFrame, lower: DataFrame, facts: DataFrame, *, anchor: str = "max", wanted: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """eps (q, eps) and community (q, v): the ratio is halved while the query survives the removal in bulk of vertices whose
    bound times the ratio stays below the target. With wanted (q, v), while one component of what is left holds all of a set."""
    static, alive = settle(static), settle(members)
    rho = _lower_degree(static, alive, lower)
    top = rho.groupBy("q").agg(F.max("low").alias("top"), F.min("low").alias("bottom"), F.min(F.when(F.col("low") > 0, F.col("low"))).alias("least"), F.max(F.when(F.col("v") == F.col("q"), F.col("low"))).alias("own"))
    goal = settle(top.join(facts.select("q", "residue"), "q").select("q", (F.col("top" if anchor == "max" else "own") + F.col("residue")).alias("target"), "bottom", "least"))
    goal = settle(goal.withColumn("eps", F.when(F.col("bottom") > 0, F.col("target") / F.col("bottom")).otherwise(F.lit(math.inf))).withColumn("ratio", F.coalesce(F.col("target") / F.col("least"), F.lit(0.0))).drop("bottom", "least"))  # a larger ratio removes the same vertices
    while goal.where("ratio >= 1").limit(1).count():
        now = settle(alive.join(goal.where("ratio >= 1").select("q"), "q", "left_semi"))
        while True:
            kept = settle(_lower_degree(static, now, lower).join(goal, "q").where(F.col("ratio") * F.col("low") >= F.col("target") * (1 - 1e-12)).select("q", "v"))
            if kept.count() == now.count():
                break
            now = kept
        passed = settle(now.where("v = q").select("q") if wanted is None else _holding(static, now, wanted))
        alive = settle(alive.join(passed, "q", "left_anti").unionByName(now.join(passed, "q", "left_semi")))
        goal = settle(goal.join(passed.withColumn("ok", F.lit(True)), "q", "left").select("q", "target", F.when(F.col("ok"), F.col("ratio")).otherwise(F.col("eps")).alias("eps"), F.when(F.col("ok"), F.col("ratio") / 2).otherwise(F.lit(0.0)).alias("ratio")))
    return goal.select("q", "eps"), component(static, alive)


def local_community(g: TemporalGraph, queries: Queries, alpha: float = 0.2, *, decay: Decay = "reciprocal", method: str = "auto", prune: bool = True, stop: bool = True, anchor: str = "max") -> DataFrame:
    """q, v, eps, residue, expanded, visited, reason: one row for each member of a query's community.

    method: levels (distributed), task (the same by blocks of queries with the whole graph, `compact`), queue (one vertex at
    a time, the sequential reference, at most IN_TASK edges), or auto: task for graphs that fit, levels beyond. Of a graph too large
    for a task, task and queue take the queries' components; where these are too large as well, levels run."""
    in_task = {"task": lambda: compact.local(g, queries, alpha, decay=decay, prune=prune, stop=stop, anchor=anchor), "queue": lambda: _by_task(g, queries, alpha, decay, prune, stop, anchor)}
    method = "task" if method == "auto" and compact.fits(g, queries) else method
    if method in in_task and (found := compact.or_distributed(in_task[method])) is not None:
        return found
    members, lower, facts = expand_levels(g, queries, alpha, decay=decay, prune=prune, stop=stop)
    eps, community = shrink_levels(g.static, members, lower, facts, anchor=anchor)
    size = members.groupBy("q").agg(F.count("*").alias("expanded"))
    return community.join(eps, "q").join(facts, "q").join(size, "q").select("q", "v", "eps", "residue", "expanded", "visited", "reason")


_held: dict[object, kernels.Walks] = {}


def _walks(sent: Broadcast, decay: Decay) -> kernels.Walks:
    """One for each worker and graph."""
    name, edges = sent.value
    key = (name, str(decay))
    if key not in _held:
        _held.clear()
        _held[key] = kernels.Walks(edges, decay)
    return _held[key]


def _by_task(g: TemporalGraph, queries: Queries, alpha: float, decay: Decay, prune: bool, stop: bool, anchor: str) -> DataFrame:
    spark = g.edges.sparkSession
    if g.edges.limit(IN_TASK + 1).count() > IN_TASK:
        g = compact.near(g, queries)
        if g.edges.limit(IN_TASK + 1).count() > IN_TASK:
            raise compact.TooLarge(f"a task holds graphs of at most {IN_TASK} edges; use levels")
    edges = [(int(r["u"]), int(r["v"]), int(r["t"])) for r in g.edges.toLocalIterator()]
    sent = spark.sparkContext.broadcast((uuid.uuid4().hex, edges))

    def run(key: tuple, _: pd.DataFrame) -> pd.DataFrame:
        q, walks = int(key[0]), _walks(sent, decay)
        columns = ["q", "v", "eps", "residue", "expanded", "visited", "reason"]
        if q not in walks.times:
            return pd.DataFrame([], columns=columns)
        x = kernels.expand(walks, q, alpha, prune=prune, stop=stop)
        adj = kernels.adjacency((u, v) for u, v, _ in walks.edges)
        eps, members = kernels.shrink(adj, x["members"], x["lower"], x["residue"], q, anchor=anchor)
        return pd.DataFrame([(q, v, eps, x["residue"], len(x["members"]), len(x["visited"]), x["reason"]) for v in sorted(members)], columns=columns)

    # as many parts as tasks can run, for a query is long work on few bytes
    spread = query_table(spark, queries).repartition(spark.sparkContext.defaultParallelism, "q")
    return spread.groupBy("q").applyInPandas(run, "q bigint, v bigint, eps double, residue double, expanded bigint, visited bigint, reason string")


def local_community_multi(g: TemporalGraph, queries: Iterable[int], alpha: float = 0.2, *, start: str = "mean", decay: Decay = "reciprocal", prune: bool = True, stop: bool = True, anchor: str = "max", method: str = "auto") -> DataFrame:
    """v, eps, residue, expanded, visited, reason for a set of query vertices: one expansion from all of them with the bounds of
    the mixed walk, and a ratio that falls as long as one component holds the set. start="mean" weighs queries alike, as
    the exact method's mean does; "union" by their out-degrees. No rows where a query has no edge or no component has all.
    method: levels, task, or auto, as in local_community."""
    wanted = sorted(set(queries))
    if method == "task" or method == "auto" and compact.fits(g, wanted):
        return compact.local_multi(g, wanted, alpha, decay=decay, prune=prune, stop=stop, anchor=anchor, union=start == "union")
    spark = g.edges.sparkSession
    g = g.settled()
    q = query_table(spark, wanted)
    head = F.lit(wanted[0]).cast("bigint").alias("q")
    one_each = seeds(g, q) if start == "mean" else seeds(g, q, "union")
    share = 1 / len(wanted) if start == "mean" else 1.0
    first = settle(one_each.select(head, "src", "dst", "t", (F.col("mass") * share).alias("r")))
    if first.select("src").distinct().count() < len(wanted):
        return spark.createDataFrame([], "v bigint, eps double, residue double, expanded bigint, visited bigint, reason string")
    static, members_of = settle(g.static), q.select(head, F.col("q").alias("v"))
    members, lower, facts = expand_levels(g, wanted, alpha, decay=decay, prune=prune, stop=stop, together=first)
    eps, found = shrink_levels(static, members, lower, facts, anchor=anchor, wanted=members_of)
    found = settle(found)
    complete = _holding(static, found, members_of)
    size = members.groupBy("q").agg(F.count("*").alias("expanded"))
    return found.join(complete, "q", "left_semi").join(eps, "q").join(facts, "q").join(size, "q").select("v", "eps", "residue", "expanded", "visited", "reason")


def is_eps_community(achieved: DataFrame, best: DataFrame, eps: DataFrame) -> DataFrame:
    """q, holds from the smallest biased degree achieved (q, beta), the exact one (q, best) and the ratio (q, eps)."""
    return achieved.join(best, "q").join(eps, "q").select("q", ((F.col("beta") <= F.col("best") * (1 + 1e-9)) & ((F.col("best") <= F.col("eps") * F.col("beta") * (1 + 1e-9)) | F.col("eps").isin(math.inf))).alias("holds"))

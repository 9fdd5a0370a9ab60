"""How a walk goes on from a state (v, t): along strictly later arcs of v, with a weight that decays with the wait.

All arcs that arrive at v at time t share one state, and the weight of an arc depends on its time alone, so the transition
matrix is never made: states have a normaliser, and a flow from a state is folded by later times before it is sent
along arcs. A state without later arcs is dangling and keeps its mass.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from proxcore.graph import TemporalGraph

Decay = str | tuple[str, float]


def weight(dt: Column, decay: Decay = "reciprocal") -> Column:
    """1 / dt; exp(-rate dt); 1 / log2(1 + dt)."""
    if decay == "reciprocal":
        return F.lit(1.0) / dt
    if decay == "log":
        return F.lit(1.0) / F.log2(dt + 1.0)
    kind, rate = decay
    if kind != "exp":
        raise ValueError(f"unknown decay {decay}")
    return F.exp(-float(rate) * dt)


def norms(g: TemporalGraph, decay: Decay = "reciprocal") -> DataFrame:
    """v, t, n_out, norm, dangling for each state. The range join has only the times of one vertex on both sides."""
    later = g.occurrences.select(F.col("v").alias("w"), F.col("t").alias("t2"), F.col("n_out").alias("n2"))
    sums = g.occurrences.join(later, (F.col("v") == F.col("w")) & (F.col("t2") > F.col("t"))).groupBy("v", "t").agg(F.sum(F.col("n2") * weight(F.col("t2") - F.col("t"), decay)).alias("norm"))
    return g.occurrences.join(sums, ["v", "t"], "left").select("v", "t", "n_out", "norm", F.col("norm").isNull().alias("dangling"))


def norms_exponential(g: TemporalGraph, rate: float) -> DataFrame:
    """The same for exponential decay, by one window pass: exp(-rate (t2 - t)) is exp(rate t) exp(-rate t2), from each
    vertex's first time to keep the terms in range; a vertex's times must span less than 700 / rate."""
    from pyspark.sql import Window

    own = Window.partitionBy("v")
    shifted = g.occurrences.withColumn("s", F.col("t") - F.min("t").over(own))
    after = own.orderBy(F.desc("t")).rowsBetween(Window.unboundedPreceding, -1)
    sums = shifted.withColumn("norm", F.exp(rate * F.col("s")) * F.sum(F.col("n_out") * F.exp(-rate * F.col("s"))).over(after))
    return sums.select("v", "t", "n_out", "norm", F.col("norm").isNull().alias("dangling"))


def transition_matrix(g: TemporalGraph, decay: Decay = "reciprocal") -> DataFrame:
    """src, dst, t, src2, dst2, t2, p for each pair of arcs that follow one another, and dangling arcs to themselves; for
    small graphs, since a vertex's in-arcs meet all its out-arcs."""
    n = norms(g, decay).select(F.col("v").alias("dst"), "t", "norm", "dangling")
    state = g.arcs.join(n, ["dst", "t"])
    nxt = g.arcs.select(F.col("src").alias("src2"), F.col("dst").alias("dst2"), F.col("t").alias("t2"))
    moves = state.where("not dangling").join(nxt, (F.col("dst") == F.col("src2")) & (F.col("t2") > F.col("t"))).select("src", "dst", "t", "src2", "dst2", "t2", (weight(F.col("t2") - F.col("t"), decay) / F.col("norm")).alias("p"))
    return moves.unionByName(state.where("dangling").select("src", "dst", "t", F.col("src").alias("src2"), F.col("dst").alias("dst2"), F.col("t").alias("t2"), F.lit(1.0).alias("p")))


def check_stochastic(g: TemporalGraph, decay: Decay = "reciprocal") -> DataFrame:
    """src, dst, t, total: rows of the transition matrix, each of which sums to one."""
    return transition_matrix(g, decay).groupBy("src", "dst", "t").agg(F.sum("p").alias("total"))


def reachable_states(g: TemporalGraph, q: int) -> DataFrame:
    """v, t: states that a time-respecting walk from q can be in; by earliest arrival, in rounds."""
    from proxcore.runtime import settle

    best = settle(g.out_arcs(q).groupBy(F.col("dst").alias("v")).agg(F.min("t").alias("first")))
    earlier = best
    while True:
        step = earlier.join(g.arcs, (F.col("v") == F.col("src")) & (F.col("t") > F.col("first"))).groupBy(F.col("dst").alias("v")).agg(F.min("t").alias("first"))
        known = best.select("v", F.col("first").alias("was"))
        earlier = settle(step.join(known, "v", "left").where("was is null or first < was").select("v", "first"))
        if earlier.limit(1).count() == 0:
            break
        best = settle(best.unionByName(earlier).groupBy("v").agg(F.min("first").alias("first")))
    starts = g.out_arcs(q).select(F.col("dst").alias("v"), "t")
    later = best.join(g.arcs, (F.col("v") == F.col("src")) & (F.col("t") > F.col("first"))).select(F.col("dst").alias("v"), "t")
    return starts.unionByName(later).distinct()

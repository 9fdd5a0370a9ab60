"""Proximity: the stationary mass of a restarting, time-respecting walk, by arrival vertex; q, v, prox for each query.

Mass moves in rounds, all queries at once. A round folds the mass of states into one flow for each (query, vertex, later
time), and sends each flow along the arcs of that vertex and time. Dangling mass is banked whole and leaves; other
states bank the restart share and pass on the rest. Times ascend strictly along a walk, so the frontier runs empty
after at most as many rounds as there are times; `tol` stops earlier, with an error of at most the mass that remains.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxcore import compact
from proxcore.graph import TemporalGraph
from proxcore.runtime import query_table, settle
from proxcore.transitions import Decay, norms, transition_matrix, weight

Queries = DataFrame | Iterable[int]


def seeds(g: TemporalGraph, queries: DataFrame, start: str = "query") -> DataFrame:
    """q, src, dst, t, mass: a unit spread over each query's out-arcs; with start="union" one unit over those of all queries,
    under the least of them as q."""
    out = queries.join(g.arcs, F.col("q") == F.col("src"))
    if start == "union":
        total = out.agg(F.count("*").alias("n"), F.min("q").alias("least"))
        return out.drop("q").crossJoin(F.broadcast(total)).select(F.col("least").alias("q"), "src", "dst", "t", (F.lit(1.0) / F.col("n")).alias("mass"))
    sizes = out.groupBy("q").agg(F.count("*").alias("n"))
    return out.join(sizes, "q").select("q", "src", "dst", "t", (F.lit(1.0) / F.col("n")).alias("mass"))


def fold(frontier: DataFrame, states: DataFrame, g: TemporalGraph, alpha: float, decay: Decay) -> DataFrame:
    """q, u, t2, flow: what each arc of u at t2 receives from live states (q, v, t, mass)."""
    live = frontier.join(states.where("not dangling").select("v", "t", "norm"), ["v", "t"]).select("q", F.col("v").alias("u"), F.col("t").alias("t1"), ((1 - alpha) * F.col("mass") / F.col("norm")).alias("share"))
    times = g.occurrences.select(F.col("v").alias("w"), F.col("t").alias("t2"))
    return live.join(times, (F.col("u") == F.col("w")) & (F.col("t2") > F.col("t1"))).groupBy("q", "u", "t2").agg(F.sum(F.col("share") * weight(F.col("t2") - F.col("t1"), decay)).alias("flow"))


def prepared(g: TemporalGraph, decay: Decay = "reciprocal") -> tuple[TemporalGraph, DataFrame]:
    """The graph and its states as tables, made once for any number of queries."""
    g = g.settled()
    return g, settle(norms(g, decay))


def prox_hops(g: TemporalGraph, queries: Queries, alpha: float = 0.2, *, decay: Decay = "reciprocal", tol: float = 0.0, start: str = "query", states: DataFrame | None = None, most_rounds: int | None = None) -> DataFrame:
    """Round i holds the mass after i + 1 steps. Dead frontiers of some queries cost nothing while others go on."""
    if states is None:
        g, states = prepared(g, decay)
    out = None
    for here in _rounds(g, queries, alpha, decay, tol, start, states, most_rounds):
        bank = here.groupBy("q", "v").agg(F.sum(F.when(F.col("dangling"), F.col("mass")).otherwise(alpha * F.col("mass"))).alias("prox"))
        out = bank if out is None else out.unionByName(bank)
    return out.groupBy("q", "v").agg(F.sum("prox").alias("prox"))


def prox(g: TemporalGraph, queries: Queries, alpha: float = 0.2, *, decay: Decay = "reciprocal", states: DataFrame | None = None) -> DataFrame:
    """In tasks for a graph whose slots fit one, by rounds for others."""
    if compact.ship_slots(g) is not None:
        return compact.proximity(g, queries, alpha, decay=decay)
    return prox_hops(g, queries, alpha, decay=decay, states=states)


def _rounds(g: TemporalGraph, queries: Queries, alpha: float, decay: Decay, tol: float, start: str, states: DataFrame, most_rounds: int | None) -> Iterator[DataFrame]:
    """q, v, t, mass, dangling of each round."""
    q = query_table(g.edges.sparkSession, queries)
    frontier = seeds(g, q, start).groupBy("q", F.col("dst").alias("v"), "t").agg(F.sum("mass").alias("mass"))
    flags, rounds = states.select("v", "t", "dangling"), 0
    while True:
        here = settle(frontier.join(flags, ["v", "t"]))
        yield here
        rounds += 1
        left = here.where("not dangling").agg(F.count("*").alias("n"), F.sum("mass").alias("mass")).first()
        if not left["n"] or left["mass"] <= tol or rounds == most_rounds:
            return
        flow = fold(here.where("not dangling").select("q", "v", "t", "mass"), states, g, alpha, decay)
        frontier = flow.join(g.arcs, (F.col("u") == F.col("src")) & (F.col("t2") == F.col("t"))).groupBy("q", F.col("dst").alias("v"), "t").agg(F.sum("flow").alias("mass"))


def work_counters(g: TemporalGraph, queries: Queries, alpha: float = 0.2, *, decay: Decay = "reciprocal") -> DataFrame:
    """q, round, states, live, messages, mass: what each round of prox_hops touches. states hold mass, live ones of them pass it
    on, and messages are the arcs that it is sent along, of which a walk from any state takes each at most once a round."""
    g, states = prepared(g, decay)
    sizes = settle(g.occurrences)
    out = None
    for k, here in enumerate(_rounds(g, queries, alpha, decay, 0.0, "query", states, None)):
        first = here.where("not dangling").groupBy("q", "v").agg(F.min("t").alias("first"))
        sent = first.join(sizes, "v").where("t > first").groupBy("q").agg(F.sum("n_out").alias("messages"))
        one = here.groupBy("q").agg(F.count("*").alias("states"), F.count_if(~F.col("dangling")).alias("live"), F.sum("mass").alias("mass")).join(sent, "q", "left")
        one = one.select("q", F.lit(k + 1).cast("bigint").alias("round"), "states", "live", F.coalesce("messages", F.lit(0)).cast("bigint").alias("messages"), "mass")
        out = one if out is None else out.unionByName(one)
    return out


def prox_slabs(g: TemporalGraph, queries: Queries, alpha: float = 0.2, *, decay: Decay = "reciprocal", slab: int = 1) -> DataFrame:
    """The same by ascending slabs of times: each slab's edges are read once, and flows into later slabs wait in a table."""
    spark = g.edges.sparkSession
    g, states = prepared(g, decay)
    start = settle(seeds(g, query_table(spark, queries)).select("q", F.col("dst").alias("v"), "t", "mass"))
    low, high = g.edges.agg(F.min("t"), F.max("t")).first()
    done = start.where("false").withColumn("dangling", F.lit(False))
    waiting, flags, parts = start, states.select("v", "t", "dangling"), []
    for t in range(low or 0, (high or -1) + 1, slab):
        inside = (F.col("t") >= t) & (F.col("t") < t + slab)
        here = waiting.where(inside).groupBy("q", "v", "t").agg(F.sum("mass").alias("mass"))
        for _ in range(slab):  # within a slab a walk has as many steps as it has times
            here = settle(here.join(flags, ["v", "t"]))
            if here.limit(1).count() == 0:
                break
            parts.append(here)
            flow = fold(here.where("not dangling").select("q", "v", "t", "mass"), states, g, alpha, decay)
            moved = settle(flow.join(g.arcs, (F.col("u") == F.col("src")) & (F.col("t2") == F.col("t"))).groupBy("q", F.col("dst").alias("v"), "t").agg(F.sum("flow").alias("mass")))
            here = moved.where(inside)
            waiting = waiting.unionByName(moved.where(F.col("t") >= t + slab))
        waiting = settle(waiting.where(F.col("t") >= t + slab).groupBy("q", "v", "t").agg(F.sum("mass").alias("mass")))
    for part in parts:
        done = done.unionByName(part)
    return done.groupBy("q", "v").agg(F.sum(F.when(F.col("dangling"), F.col("mass")).otherwise(alpha * F.col("mass"))).alias("prox"))


def prox_power(g: TemporalGraph, queries: Queries, alpha: float = 0.2, *, decay: Decay = "reciprocal", tol: float = 1e-12, most_rounds: int = 400) -> DataFrame:
    """Power iteration over explicit arc pairs: the slow reference, for small graphs."""
    spark = g.edges.sparkSession
    matrix = settle(transition_matrix(g, decay))
    start = settle(seeds(g, query_table(spark, queries)))
    x = start
    for _ in range(most_rounds):
        step = x.join(matrix, ["src", "dst", "t"]).groupBy("q", F.col("src2").alias("src"), F.col("dst2").alias("dst"), F.col("t2").alias("t")).agg(((1 - alpha) * F.sum(F.col("mass") * F.col("p"))).alias("mass"))
        fresh = settle(step.unionByName(start.withColumn("mass", alpha * F.col("mass"))).groupBy("q", "src", "dst", "t").agg(F.sum("mass").alias("mass")))
        gap = fresh.join(x.withColumnRenamed("mass", "old"), ["q", "src", "dst", "t"], "full").agg(F.max(F.abs(F.coalesce("mass", F.lit(0.0)) - F.coalesce("old", F.lit(0.0))))).first()[0] or 0.0
        x = fresh
        if gap <= tol:
            break
    return x.groupBy("q", F.col("dst").alias("v")).agg(F.sum("mass").alias("prox"))


def prox_walks(g: TemporalGraph, queries: Queries, alpha: float = 0.2, *, depth: int = 3, decay: Decay = "reciprocal") -> DataFrame:
    """The walk series up to a depth: walks of i + 1 arcs weigh alpha (1 - alpha)^i. A lower bound, short by (1 - alpha)^depth
    at most. Dangling arcs repeat themselves."""
    spark = g.edges.sparkSession
    matrix = settle(transition_matrix(g, decay))
    walks = seeds(g, query_table(spark, queries))
    out = walks.select("q", F.col("dst").alias("v"), (alpha * F.col("mass")).alias("w"))
    for i in range(1, depth):
        walks = settle(walks.join(matrix, ["src", "dst", "t"]).select("q", F.col("src2").alias("src"), F.col("dst2").alias("dst"), F.col("t2").alias("t"), (F.col("mass") * F.col("p")).alias("mass")))
        out = out.unionByName(walks.select("q", F.col("dst").alias("v"), (alpha * (1 - alpha) ** i * F.col("mass")).alias("w")))
    return out.groupBy("q", "v").agg(F.sum("w").alias("prox"))


def prox_sampled(g: TemporalGraph, queries: Queries, alpha: float = 0.2, *, walks: int = 1000, seed: int = 7, decay: Decay = "reciprocal") -> DataFrame:
    """An unbiased estimate from walks that stop with probability alpha at each state, or where they dangle."""
    spark = g.edges.sparkSession
    g, states = prepared(g, decay)
    numbered = seeds(g, query_table(spark, queries)).select("q", "dst", "t", F.row_number().over(_by("q")).alias("k"), F.count("*").over(_all("q")).alias("n"))
    flags = states.select("v", "t", "dangling")
    walker = query_table(spark, queries).crossJoin(spark.range(walks).select(F.col("id").alias("walk")))  # a fixed number for each query
    u = lambda i: (F.pmod(F.xxhash64("q", "walk", F.lit(i), F.lit(seed)), F.lit(1 << 40)) / float(1 << 40))
    now = walker.join(numbered.select("q", "n").distinct(), "q").withColumn("k", (F.floor(u(0) * F.col("n")) + 1).cast("int")).drop("n").join(numbered.drop("n"), ["q", "k"]).select("q", "walk", F.col("dst").alias("v"), "t")
    ends, i = None, 1
    while True:
        here = settle(now.join(flags, ["v", "t"]))
        stop = here.where(F.col("dangling") | (u(i) < alpha)).select("q", "v")
        ends = stop if ends is None else ends.unionByName(stop)
        going = here.where(~(F.col("dangling") | (u(i) < alpha)))
        if going.limit(1).count() == 0:
            break
        nxt = g.arcs.select("src", "dst", F.col("t").alias("t2"))
        # the arc with the least exponential clock of rate g(dt) is drawn in proportion to its weight
        clock = -F.log((F.pmod(F.xxhash64("q", "walk", "dst", "t2", F.lit(i), F.lit(seed)), F.lit(1 << 40)) + 1) / float(1 << 40)) / weight(F.col("t2") - F.col("t"), decay)
        now = going.join(nxt, (F.col("v") == F.col("src")) & (F.col("t2") > F.col("t"))).groupBy("q", "walk").agg(F.min_by(F.struct("dst", "t2"), clock).alias("s")).select("q", "walk", F.col("s.dst").alias("v"), F.col("s.t2").alias("t"))
        i += 1
    return ends.groupBy("q", "v").agg((F.count("*") / float(walks)).alias("prox"))


def _by(key: str):  # noqa: ANN202
    from pyspark.sql import Window

    return Window.partitionBy(key).orderBy("t", "dst")


def _all(key: str):  # noqa: ANN202
    from pyspark.sql import Window

    return Window.partitionBy(key)


def prox_multi(prox: DataFrame, combine: str = "mean") -> DataFrame:
    """v, prox over all queries of a table (q, v, prox); a vertex that a query misses has 0 there."""
    total = prox.agg(F.count_distinct("q").alias("n"))
    one = prox.groupBy("v").agg(F.sum("prox").alias("s"), F.min("prox").alias("least"), F.exp(F.sum(F.log("prox"))).alias("product"), F.count_if(F.col("prox") > 0).alias("k")).crossJoin(F.broadcast(total))
    pick = {"mean": F.col("s") / F.col("n"), "min": F.when(F.col("k") == F.col("n"), F.col("least")).otherwise(0.0), "product": F.when(F.col("k") == F.col("n"), F.col("product")).otherwise(0.0)}[combine]
    return one.select("v", pick.alias("prox"))


def ppr_static(g: TemporalGraph, queries: Queries, alpha: float = 0.2, *, tol: float = 1e-9, most_rounds: int = 200, rounds: int | None = None) -> DataFrame:
    """The classic personalised score on the graph without times: q, v, prox."""
    spark = g.edges.sparkSession
    static = settle(g.static)
    degree = static.groupBy("v").agg(F.count("*").alias("d"))
    out_of = settle(static.join(degree, "v"))
    mass = query_table(spark, queries).select("q", F.col("q").alias("v"), F.lit(1.0).alias("mass"))
    out, left = None, 1.0
    for i in range(rounds or most_rounds):
        mass = settle(mass)
        bank = mass.select("q", "v", (alpha * F.col("mass")).alias("prox"))
        out = bank if out is None else settle(out.unionByName(bank).groupBy("q", "v").agg(F.sum("prox").alias("prox")))
        left *= 1 - alpha
        if rounds is None and left <= tol or i + 1 == rounds:
            break
        mass = mass.join(out_of, "v").groupBy("q", F.col("nbr").alias("v")).agg(((1 - alpha) * F.sum(F.col("mass") / F.col("d"))).alias("mass"))
    return out.groupBy("q", "v").agg(F.sum("prox").alias("prox"))


def push_static(g: TemporalGraph, queries: Queries, alpha: float = 0.2, *, least: float = 1e-4) -> DataFrame:
    """q, v, reserve, residue: pushes while a vertex holds a residue of at least `least` times its degree."""
    spark = g.edges.sparkSession
    static = settle(g.static)
    degree = settle(static.groupBy("v").agg(F.count("*").alias("d")))
    state = settle(query_table(spark, queries).select("q", F.col("q").alias("v"), F.lit(0.0).alias("reserve"), F.lit(1.0).alias("residue")))
    while True:
        hot = state.join(degree, "v").where(F.col("residue") >= least * F.col("d"))
        if hot.limit(1).count() == 0:
            return state
        sent = hot.join(static, "v").groupBy("q", F.col("nbr").alias("v")).agg(F.sum((1 - alpha) * F.col("residue") / F.col("d")).alias("add"))
        flat = state.join(degree, "v", "left").withColumn("hot", F.coalesce(F.col("residue") >= least * F.col("d"), F.lit(False)))
        flat = flat.select("q", "v", (F.col("reserve") + F.when(F.col("hot"), alpha * F.col("residue")).otherwise(0.0)).alias("reserve"), F.when(F.col("hot"), 0.0).otherwise(F.col("residue")).alias("residue"))
        state = settle(flat.unionByName(sent.select("q", "v", F.lit(0.0).alias("reserve"), F.col("add").alias("residue"))).groupBy("q", "v").agg(F.sum("reserve").alias("reserve"), F.sum("residue").alias("residue")))


def check_mass(prox: DataFrame) -> DataFrame:
    """q, mass: the sum of each query's proximity, which is one."""
    return prox.groupBy("q").agg(F.sum("prox").alias("mass"))

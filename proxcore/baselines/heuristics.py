"""Baselines that are hard to solve: periodic cliques, by an exact search, and the greedy inefficiency connector.

The clique search has a task for each query, start, period and second member, over the edges among the common neighbours
of both; the connector is one task for each query over the two-step ball of its tree."""

from __future__ import annotations

import heapq
from collections import defaultdict
from collections.abc import Iterable

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxcore.graph import TemporalGraph
from proxcore.kernels import Edge
from proxcore.proximity import Queries
from proxcore.runtime import Growing, query_table, settle


def ball(g: TemporalGraph, queries: Queries, hops: int = 1) -> DataFrame:
    """q, u, v, t: edges among vertices within some hops of each query."""
    static = settle(g.static)
    near = query_table(g.edges.sparkSession, queries).select("q", F.col("q").alias("v"))
    for _ in range(hops):
        near = settle(near.unionByName(near.join(static, "v").select("q", F.col("nbr").alias("v"))).distinct())
    return near.select("q", F.col("v").alias("u")).join(g.edges, "u").join(near, ["q", "v"], "left_semi").select("q", "u", "v", "t")


def periodic_edges(g: TemporalGraph, sigma: int = 3) -> DataFrame:
    """u, v, start, period: edges at sigma equally spaced times."""
    e = g.edges
    out = e.select("u", "v", F.col("t").alias("start")).join(e.select("u", "v", F.col("t").alias("second")), ["u", "v"]).where("second > start").withColumn("period", F.col("second") - F.col("start"))
    for k in range(2, sigma):
        out = out.join(e.select(F.col("u"), F.col("v"), F.col("t").alias("next")), ["u", "v"]).where(F.col("next") == F.col("start") + k * F.col("period")).drop("next")
    return out.select("u", "v", "start", "period")


def largest_clique(adj: dict[int, set[int]], start: Iterable[int] = ()) -> list[int]:
    """The largest clique among the given vertices (all by default), the least by members at ties: branch and bound, where a
    greedy colouring of the vertices at hand says how many of them a clique can have at most."""
    best: list[int] = []

    def coloured(rest: list[int]) -> list[tuple[int, int]]:
        """Vertices by colour, each with the number of colours up to its own."""
        out, left, colour = [], rest, 0
        while left:
            colour += 1
            same: list[int] = []
            for v in left:
                if not any(w in adj[v] for w in same):
                    same.append(v)
            taken = set(same)
            out += [(v, colour) for v in same]
            left = [v for v in left if v not in taken]
        return out

    def grow(clique: list[int], rest: list[int]) -> None:
        nonlocal best
        if not rest:
            own = sorted(clique)
            if (len(own), [-x for x in own]) > (len(best), [-x for x in best]):
                best = own
            return
        open_ = coloured(rest)
        alive = set(rest)
        for v, colours in reversed(open_):
            if len(clique) + colours < len(best):  # one as large may still have lesser members
                return
            grow([*clique, v], [w for w in rest if w in alive and w in adj[v]])
            alive.discard(v)
        return

    grow([], sorted(start or adj))
    return best


def periodic_clique(g: TemporalGraph, queries: Queries, sigma: int = 3, min_size: int = 3) -> DataFrame:
    """q, v, start, period, exact (true): the largest set with the query whose pairs all meet at sigma equally spaced times; of
    equally large ones the earliest start, the shortest period, then the least members."""
    spark = g.edges.sparkSession
    timed = settle(periodic_edges(g, sigma))
    both = timed.select("start", "period", F.explode(F.array(F.struct("u", "v"), F.struct(F.col("v").alias("u"), F.col("u").alias("v")))).alias("e")).select("start", "period", "e.u", "e.v")
    near = settle(query_table(spark, queries).join(both, F.col("u") == F.col("q")).select("q", "start", "period", F.col("v").alias("w")))
    # a branch: the query and its least other member; what may follow are greater neighbours of both
    key = ["q", "start", "period"]
    later = near.join(both.select("start", "period", F.col("u").alias("w"), F.col("v").alias("x")), ["start", "period", "w"]).where("x > w").join(near.select(*key, F.col("w").alias("x")), [*key, "x"])
    later = settle(later.select(*key, "w", "x"))
    inner = later.join(timed.select("start", "period", F.col("u").alias("x"), F.col("v").alias("y")), ["start", "period", "x"]).join(later.select(*key, "w", F.col("x").alias("y")), [*key, "w", "y"])
    parts = inner.select(*key, "w", "x", "y").unionByName(later.select(*key, "w", "x", F.lit(None).cast("bigint").alias("y")))

    def run(at: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        adj: dict[int, set[int]] = {int(x): set() for x in pdf["x"]}
        closed = pdf.dropna(subset=["y"])
        for x, y in zip(closed["x"].astype("int64").tolist(), closed["y"].astype("int64").tolist(), strict=True):
            adj[x].add(y)
            adj[y].add(x)
        q, start, period, w = (int(k) for k in at)
        found = sorted([q, w, *largest_clique(adj)])
        return pd.DataFrame({"q": [q], "start": [start], "period": [period], "members": [found]})

    branches = parts.groupBy(*key, "w").applyInPandas(run, "q bigint, start bigint, period bigint, members array<bigint>")
    pairs = near.select(*key, F.array_sort(F.array("q", "w")).alias("members"))
    size = F.size("members")
    # of equally large ones the least by start, period and members
    every = branches.unionByName(pairs).where(size >= min_size).withColumn("size", size)
    top = every.groupBy("q").agg(F.max("size").alias("size"))
    best = every.join(top, ["q", "size"]).groupBy("q").agg(F.min(F.struct("start", "period", "members")).alias("b"))
    return best.select("q", F.explode("b.members").alias("v"), "b.start", "b.period", F.lit(True).alias("exact"))


def temporal_distances(edges: Iterable[Edge], members: Iterable[int], mix: float) -> dict[tuple[int, int], float]:
    """From each member to the others along ascending times: the least mix of elapsed time plus one and hops."""
    out_of: dict[int, list[tuple[int, int]]] = defaultdict(list)
    for u, v, t in edges:
        out_of[u].append((t, v))
        out_of[v].append((t, u))
    dist: dict[tuple[int, int], float] = {}
    for s in members:
        heap = [(mix * 1 + (1 - mix) * 1, 1, t, t, v) for t, v in out_of[s]]
        heapq.heapify(heap)
        seen: set[tuple[int, int]] = set()
        while heap:
            d, hops, first, t, v = heapq.heappop(heap)
            if (v, t) in seen:
                continue
            seen.add((v, t))
            if v != s:
                dist.setdefault((s, v), d)
            for t2, w in out_of[v]:
                if t2 > t:
                    heapq.heappush(heap, (mix * (t2 - first + 1) + (1 - mix) * (hops + 1), hops + 1, first, t2, w))
    return dist


def query_tree(static: DataFrame, wanted: list[int]) -> DataFrame | None:
    """v: a tree that joins a set of vertices, by shortest paths from the least of them; None where they aren't joined. Paths are
    at most as many edges together as the set's other vertices times the best tree."""
    spark = static.sparkSession
    reached = Growing(spark.createDataFrame([(wanted[0], None)], "v bigint, parent bigint"))
    frontier, left = reached.table, len(set(wanted)) - 1
    rest = query_table(spark, wanted[1:]).withColumnRenamed("q", "v") if left else None
    while left:
        step = frontier.select("v").join(static, "v").groupBy(F.col("nbr").alias("v")).agg(F.min(F.col("v")).alias("parent"))
        frontier = reached.add(step.join(reached.table, "v", "left_anti"))
        if frontier.limit(1).count() == 0:
            return None
        left -= frontier.join(rest, "v").count()
    tree = Growing(query_table(spark, wanted).withColumnRenamed("q", "v"))
    up = tree.table
    while True:
        up = tree.add(reached.table.join(up, "v", "left_semi").where("parent is not null").select(F.col("parent").alias("v")).distinct().join(tree.table, "v", "left_anti"))
        if up.limit(1).count() == 0:
            return tree.table


def _grown(own: list[Edge], s: set[int], k: float, mix: float) -> tuple[set[int], float]:
    """From a start set, the neighbour that raises the sum of pair efficiencies most is added until none does."""

    def value(members: set[int], inner: list[Edge]) -> float:
        d = temporal_distances(inner, members, mix)
        total, order = 0.0, sorted(members)
        for i, a in enumerate(order):
            for b in order[i + 1 :]:
                total += k * (1 / d.get((a, b), float("inf")) + 1 / d.get((b, a), float("inf"))) - 1
        return total

    of: dict[int, list[Edge]] = defaultdict(list)
    for e in own:
        of[e[0]].append(e)
        of[e[1]].append(e)
    inner = [e for e in own if e[0] in s and e[1] in s]
    score, alone = value(s, inner), len(s) == 1
    while True:
        near = {x for v in s for e in of[v] for x in e[:2]} - s
        tries = [(value(s | {w}, inner + [e for e in of[w] if e[0] in s or e[1] in s]), -w) for w in near]
        if not tries or (max(tries)[0] <= score and not alone):
            return s, score
        score, w = max(tries)
        inner += [e for e in of[-w] if e[0] in s or e[1] in s]
        s, alone = s | {-w}, False


def inefficiency_community(g: TemporalGraph, queries: Queries, k: float = 0.5, mix: float = 0.5) -> DataFrame:
    """q, v, score, exact (false): grown from the query by the neighbour that raises the sum of pair efficiencies most, until none does."""

    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        q = int(key[0])
        s, score = _grown(list(zip(pdf["u"].tolist(), pdf["v"].tolist(), pdf["t"].tolist(), strict=True)), {q}, k, mix)
        return pd.DataFrame([(q, v, score, False) for v in sorted(s)], columns=["q", "v", "score", "exact"])

    return ball(g, queries, 2).groupBy("q").applyInPandas(run, "q bigint, v bigint, score double, exact boolean")


def inefficiency_community_multi(g: TemporalGraph, queries: Iterable[int], k: float = 0.5, mix: float = 0.5) -> DataFrame:
    """v, score, exact (false) for a set of query vertices: grown in the same way from a tree that joins them."""
    wanted = sorted(set(queries))
    g = g.settled()
    tree = query_tree(settle(g.static), wanted)
    schema = "v bigint, score double, exact boolean"
    if tree is None:
        return g.edges.sparkSession.createDataFrame([], schema)
    start = [r["v"] for r in tree.collect()]  # paths between the query vertices
    head = start[0]
    near = ball(g, start, 2).select(F.lit(head).alias("q"), "u", "v", "t").distinct()

    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        s, score = _grown(list(zip(pdf["u"].tolist(), pdf["v"].tolist(), pdf["t"].tolist(), strict=True)), set(start), k, mix)
        return pd.DataFrame([(v, score, False) for v in sorted(s)], columns=["v", "score", "exact"])

    return near.groupBy("q").applyInPandas(run, schema)

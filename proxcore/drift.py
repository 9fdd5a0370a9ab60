"""Drift: communities that an objective improves by members which are far from the query."""

from __future__ import annotations

from collections.abc import Callable
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxcore.cores import biased_degree, core_numbers
from proxcore.graph import TemporalGraph
from proxcore.kernels import Adjacency, Edge, adjacency, smallest

Objective = Callable[[list[Edge], frozenset[int]], float]


def _inside(edges: list[Edge], s: frozenset[int]) -> list[Edge]:
    return [e for e in edges if e[0] in s and e[1] in s]


def burst_density(edges: list[Edge], s: frozenset[int]) -> float:
    """Inner temporal edges over size times number of inner times."""
    own = _inside(edges, s)
    return len(own) / (len(s) * len({t for _, _, t in own})) if own else 0.0


def interval_degree(interval: frozenset[int]) -> Objective:
    """The smallest degree among pairs that meet at every time of an interval."""

    def f(edges: list[Edge], s: frozenset[int]) -> float:
        met: dict[tuple[int, int], set[int]] = {}
        for u, v, t in _inside(edges, s):
            met.setdefault((u, v), set()).add(t)
        adj = adjacency(p for p, ts in met.items() if interval <= ts)
        return float(min(len(adj[v]) for v in s)) if s else 0.0

    return f


def persistent_size(k: int, theta: int, tau: int) -> Objective:
    """The size, if every window of theta times that starts in a run of tau steps gives each member k neighbours inside."""

    def f(edges: list[Edge], s: frozenset[int]) -> float:
        own = _inside(edges, s)
        good = 0
        for start in sorted({t for _, _, t in own}):
            adj = adjacency((u, v) for u, v, t in own if start <= t < start + theta)
            good += all(len(adj[v]) >= k for v in s)
        return float(len(s)) if good >= tau else 0.0

    return f


def periodic_clique(sigma: int) -> Objective:
    """1 if all pairs meet at each of sigma equally spaced times."""

    def f(edges: list[Edge], s: frozenset[int]) -> float:
        pairs = list(combinations(sorted(s), 2))
        have = set(_inside(edges, s))
        times = sorted({t for _, _, t in have})
        return float(len(s) > 1 and any(all((u, v, a + k * (b - a)) in have for u, v in pairs for k in range(sigma)) for a in times for b in times if b > a))

    return f


def inefficiency(k: float = 0.5, mix: float = 0.5) -> Objective:
    """Sum over pairs of k (1 / d(u, v) + 1 / d(v, u)) - 1, where d mixes hops and elapsed time of the quickest inner path."""
    from proxcore.baselines.heuristics import temporal_distances

    def f(edges: list[Edge], s: frozenset[int]) -> float:
        d = temporal_distances(_inside(edges, s), s, mix)
        return sum(k * (1 / d.get((u, v), float("inf")) + 1 / d.get((v, u), float("inf"))) - 1 for u, v in combinations(sorted(s), 2))

    return f


def smallest_biased(weight: dict[int, float]) -> Objective:
    return lambda edges, s: smallest(adjacency((u, v) for u, v, _ in edges), weight, set(s)) if s else 0.0


def free_rider(f: Objective, edges: list[Edge], optimum: frozenset[int], found: frozenset[int]) -> bool:
    """The objective isn't lowered by uniting a community with a global optimum."""
    return f(edges, optimum | found) >= f(edges, found)


def drifted(f: Objective, edges: list[Edge], weight: dict[int, float], optimum: frozenset[int], found: frozenset[int]) -> set[int]:
    """The optimum's members beyond the community, if they ride free and don't raise the smallest biased degree; else none."""
    adj: Adjacency = adjacency((u, v) for u, v, _ in edges)
    extra = set(optimum - found)
    worse = smallest(adj, weight, set(optimum | found)) <= smallest(adj, weight, set(found))
    return extra if extra and worse and free_rider(f, edges, optimum, found) else set()


def _inner_density(g: TemporalGraph, members: DataFrame, name: str) -> DataFrame:
    near = members.select("q", F.col("v").alias("u")).join(g.edges, "u").join(members.select("q", "v"), ["q", "v"], "left_semi")
    inner = near.groupBy("q").agg(F.count("*").alias("m"), F.count_distinct("t").alias("times"))
    sized = members.groupBy("q").agg(F.count_distinct("v").alias("n")).join(inner, "q", "left")
    return sized.select("q", F.coalesce(F.expr("try_divide(m * 1.0D, n * times)"), F.lit(0.0)).alias(name))


def burst_densities(g: TemporalGraph, members: DataFrame) -> DataFrame:
    """q, density: burst_density of each query's set (q, v), as a table."""
    return _inner_density(g, members, "density")


def interval_degrees(g: TemporalGraph, members: DataFrame, start: int, end: int) -> DataFrame:
    """q, degree: the smallest degree among members of pairs that meet at every time of [start, end]."""
    pairs = g.slice(start, end + 1).edges.groupBy("u", "v").agg(F.count_distinct("t").alias("n")).where(F.col("n") == end - start + 1)
    both = pairs.select(F.explode(F.array(F.struct(F.col("u").alias("v"), F.col("v").alias("nbr")), F.struct(F.col("v"), F.col("u").alias("nbr")))).alias("e")).select("e.v", "e.nbr")
    degree = members.select("q", "v").join(both, "v").join(members.select("q", F.col("v").alias("nbr")), ["q", "nbr"]).groupBy("q", "v").agg(F.count("*").alias("d"))
    return members.select("q", "v").join(degree, ["q", "v"], "left").groupBy("q").agg(F.min(F.coalesce("d", F.lit(0))).alias("degree"))


def free_riders(g: TemporalGraph, optimum: DataFrame, found: DataFrame) -> DataFrame:
    """q, rides: uniting a community (q, v) with an optimum (q, v) of the burst density doesn't lower it."""
    union = found.select("q", "v").unionByName(optimum.select("q", "v")).distinct()
    return _inner_density(g, union, "both").join(_inner_density(g, found, "own"), "q").select("q", (F.col("both") >= F.col("own")).alias("rides"))


def drifted_members(g: TemporalGraph, static: DataFrame, weights: DataFrame, optimum: DataFrame, found: DataFrame) -> DataFrame:
    """q, v: the optimum's members beyond the community where they ride free and don't raise the smallest biased degree."""
    union = found.select("q", "v").unionByName(optimum.select("q", "v")).distinct()
    least = lambda s, name: biased_degree(static, weights, s).groupBy("q").agg(F.min("rho").alias(name))
    worse = least(union, "both").join(least(found.select("q", "v"), "own"), "q").where("both <= own").select("q")
    bad = free_riders(g, optimum, found).where("rides").select("q").join(worse, "q", "left_semi")
    return optimum.select("q", "v").distinct().join(found.select("q", "v"), ["q", "v"], "left_anti").join(bad, "q", "left_semi")


def drift_report(static: DataFrame, weights: DataFrame, members: DataFrame) -> DataFrame:
    """q, size, drifted, share: members whose core number is below the query's, the part of a community that drifted."""
    cores = core_numbers(static, weights)
    own = cores.where("v = q").select("q", F.col("core").alias("beta"))
    judged = members.select("q", "v").join(cores, ["q", "v"], "left").join(own, "q", "left").select("q", (F.coalesce("core", F.lit(0)) < F.coalesce("beta", F.lit(0))).alias("away"))
    return judged.groupBy("q").agg(F.count("*").alias("size"), F.count_if("away").alias("drifted"), F.avg(F.col("away").cast("double")).alias("share"))


def no_drift(static: DataFrame, weights: DataFrame, community: DataFrame, others: DataFrame) -> DataFrame:
    """q, holds: uniting with other sets (q, v) that add a member lowers the smallest biased degree, so the community is maximal."""
    own = biased_degree(static, weights, community).groupBy("q").agg(F.min("rho").alias("own"))
    union = community.select("q", "v").unionByName(others.select("q", "v")).distinct()
    more = union.groupBy("q").agg(F.count("*").alias("n")).join(community.groupBy("q").agg(F.count("*").alias("k")), "q").where("n > k")
    both = biased_degree(static, weights, union).groupBy("q").agg(F.min("rho").alias("both"))
    return own.join(more, "q", "left").join(both, "q", "left").select("q", (F.col("n").isNull() | (F.col("both") < F.col("own"))).alias("holds"))

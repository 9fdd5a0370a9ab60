"""Quality, overlap and cost measures; a community is a table of members (q, v)."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable, Iterator

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from proxcore.cores import biased_degree
from proxcore.graph import TemporalGraph
from proxcore.runtime import query_table


def _ends(g: TemporalGraph, members: DataFrame) -> DataFrame:
    """q, u, v, t, both: edges with an end in a query's set, once each."""
    touch = members.select("q", F.col("v").alias("m")).join(g.arcs, F.col("m") == F.col("src")).select("q", F.least("src", "dst").alias("u"), F.greatest("src", "dst").alias("v"), "t")
    return touch.groupBy("q", "u", "v", "t").agg((F.count("*") > 1).alias("both"))


def temporal_density(g: TemporalGraph, members: DataFrame) -> DataFrame:
    """q, density: twice the inner temporal edges over size (size - 1) times the inner times; null where that is none."""
    inner = _ends(g, members).where("both").groupBy("q").agg(F.count("*").alias("m"), F.count_distinct("t").alias("times"))
    return members.groupBy("q").agg(F.count_distinct("v").alias("n")).join(inner, "q", "left").select("q", F.expr("try_divide(2.0D * m, n * (n - 1.0D) * times)").alias("density"))


def temporal_conductance(g: TemporalGraph, members: DataFrame) -> DataFrame:
    """q, conductance: temporal edges that leave the set over the lesser volume of both sides; null where one is empty."""
    touched = _ends(g, members).groupBy("q").agg(F.count_if(~F.col("both")).alias("cut"), F.count_if(F.col("both")).alias("inner"))
    total = g.edges.agg((2 * F.count("*")).alias("volume"))
    sides = touched.crossJoin(F.broadcast(total)).select("q", "cut", (F.col("cut") + 2 * F.col("inner")).alias("own"), "volume")
    return sides.select("q", F.expr("try_divide(cut * 1.0D, least(own, volume - own))").alias("conductance"))


def static_conductance(static: DataFrame, members: DataFrame) -> DataFrame:
    """The same on the graph without times: q, conductance."""
    out = members.join(static, "v").join(members.select("q", F.col("v").alias("nbr"), F.lit(True).alias("inside")), ["q", "nbr"], "left").groupBy("q").agg(F.count("*").alias("own"), F.count_if(F.col("inside").isNull()).alias("cut"))
    return out.crossJoin(F.broadcast(static.agg(F.count("*").alias("volume")))).select("q", F.expr("try_divide(cut * 1.0D, least(own, volume - own))").alias("conductance"))


def min_biased_degree(static: DataFrame, weights: DataFrame, members: DataFrame) -> DataFrame:
    """q, rho."""
    return biased_degree(static, weights, members).groupBy("q").agg(F.min("rho").alias("rho"))


def overlap_scores(found: DataFrame, truth: DataFrame) -> DataFrame:
    """q, precision, recall, f1 of members against members."""
    both = found.select("q", "v", F.lit(1).alias("a")).join(truth.select("q", "v", F.lit(1).alias("b")), ["q", "v"], "full")
    n = both.groupBy("q").agg(F.count_if(F.col("a").isNotNull() & F.col("b").isNotNull()).alias("hit"), F.count("a").alias("k"), F.count("b").alias("t"))
    return n.select("q", F.expr("try_divide(hit * 1.0D, k)").alias("precision"), F.expr("try_divide(hit * 1.0D, t)").alias("recall"), F.expr("try_divide(2.0D * hit, k + t)").alias("f1"))


def true_ratio(exact: DataFrame, achieved: DataFrame) -> DataFrame:
    """q, ratio: the exact smallest biased degree over the achieved one; both are (q, rho)."""
    return exact.join(achieved.select("q", F.col("rho").alias("got")), "q").select("q", F.expr("try_divide(rho * 1.0D, got)").alias("ratio"))


def average_rank(values: DataFrame, *, lower_is_better: bool = True) -> DataFrame:
    """method, mean_rank over the datasets of (dataset, method, value)."""
    order = F.asc_nulls_last("value") if lower_is_better else F.desc_nulls_last("value")
    return values.withColumn("place", F.rank().over(Window.partitionBy("dataset").orderBy(order))).groupBy("method").agg(F.avg("place").alias("mean_rank"))


def timed(make: Callable[[], DataFrame]) -> tuple[DataFrame, float]:
    """A table and the seconds that working it out took."""
    began = time.perf_counter()
    df = make()
    df.write.format("noop").mode("overwrite").save()
    return df, time.perf_counter() - began


def expanded_share(g: TemporalGraph, found: DataFrame) -> DataFrame:
    """q, share: expanded vertices of the local method over all vertices."""
    n = g.arcs.agg(F.count_distinct("src").alias("n"))
    return found.select("q", "expanded").distinct().crossJoin(F.broadcast(n)).select("q", (F.col("expanded") / F.col("n")).alias("share"))


def array_bytes(g: TemporalGraph, queries: DataFrame, alpha: float = 0.2) -> DataFrame:
    """method, bytes, largest: bytes that the array path holds in a task, from the arrays themselves: the graph's, and what the exact
    and the local method add for one query at a time (mean and largest over queries). A graph that isn't broadcast (`compact.ship`) has them
    made once, by one task; where they are too large for that too, the same numbers come from the counted lengths of the arrays."""
    from proxcore import compact

    def block(a: compact.Arrays, qs: list[int]) -> Iterator[dict]:
        graph = a.nbytes()
        for q in qs:
            scores = a.proximity([q], alpha)
            members, lower, _ = a.expand(q, alpha)
            # states and vertices of the walk, and members with their bounds and the residues of arcs
            exact = scores.nbytes + 8 * len(a.state_v) + 8 * a.n
            local = members.nbytes + lower.nbytes + 8 * len(a.arc_src)
            yield {"method": ["graph", "exact", "local"], "bytes": [graph, graph + exact, graph + local]}

    schema = "method string, bytes bigint"
    rows = compact.or_distributed(lambda: compact.answer(g, queries, "reciprocal", schema, block))
    if rows is None:
        near = compact.near(g, queries)
        rows = compact.or_distributed(lambda: compact.alone(near, queries, "reciprocal", schema, block))
    if rows is None:
        rows = _counted_bytes(near, queries)
    return rows.groupBy("method").agg(F.avg("bytes").cast("bigint").alias("bytes"), F.max("bytes").alias("largest"))


def _counted_bytes(g: TemporalGraph, queries: DataFrame | Iterable[int]) -> DataFrame:
    """method, bytes for each query that the graph has: of array_bytes, by the lengths of the arrays."""
    from proxcore import compact

    x = compact.lengths(g)
    graph = compact.bytes_of(x)
    exact = 8 * x["n"] + 8 * x["states"] + 8 * x["n"]
    local = x["n"] + 8 * x["n"] + 16 * x["m"]
    held = F.array(*(F.struct(F.lit(name).alias("method"), F.lit(size).cast("bigint").alias("bytes")) for name, size in (("graph", graph), ("exact", graph + exact), ("local", graph + local))))
    own = query_table(g.spark, queries).join(g.arcs.select(F.col("src").alias("q")), "q", "left_semi")
    return own.select(F.explode(held).alias("x")).select("x.method", "x.bytes")


def memory_report(g: TemporalGraph, **tables: DataFrame) -> DataFrame:
    """name, n_rows, bytes: rows and eight bytes for each number, of the graph and of a method's tables."""
    parts = {"graph": g.edges, **tables}
    out = None
    for name, df in parts.items():
        one = df.agg(F.count("*").alias("n_rows")).select(F.lit(name).alias("name"), "n_rows", (F.col("n_rows") * 8 * len(df.columns)).alias("bytes"))
        out = one if out is None else out.unionByName(one)
    return out

"""Temporal graphs: undirected edges (u, v, t) with u < v, each once; loops are dropped, two times are two edges."""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from proxcore.runtime import settle

#: Seconds in the units that coarsen() and from_edges() know.
UNITS = {"second": 1, "minute": 60, "ten_minute": 600, "hour": 3600, "day": 86_400}


def portable_hash(v: F.Column) -> F.Column:
    """A multiplicative hash that other SQL engines can repeat."""
    return ((v % 2147483648) * 2654435761) % 4294967296


class TemporalGraph:
    #: v, t of graphs in which all who share a time meet (`SlotGraph`).
    slots: DataFrame | None = None

    def __init__(self, edges: DataFrame):
        self.edges = edges

    @property
    def spark(self) -> SparkSession:
        return self.edges.sparkSession

    @classmethod
    def from_edges(cls, df: DataFrame, u: str = "u", v: str = "v", t: str = "t", unit: str | None = None) -> TemporalGraph:
        """Canonical edges of any table. With a unit, t is a timestamp or a number of seconds, and is cut to the unit."""
        at = F.col(t)
        if unit in ("month", "year"):
            at = F.year(at) * 12 + F.month(at) if unit == "month" else F.year(at)
        elif unit is not None:
            seconds = F.unix_timestamp(at.cast("timestamp")) if dict(df.dtypes)[t].startswith("timestamp") else at
            at = F.floor(seconds / UNITS[unit])
        rows = df.select(F.col(u).cast("bigint").alias("a"), F.col(v).cast("bigint").alias("b"), at.cast("bigint").alias("t")).where("a <> b and t is not null")
        return cls(rows.select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v"), "t").distinct())

    def settled(self) -> TemporalGraph:
        return TemporalGraph(settle(self.edges))

    @cached_property
    def arcs(self) -> DataFrame:
        """src, dst, t: both directions; narrow."""
        both = F.array(F.struct(F.col("u").alias("src"), F.col("v").alias("dst")), F.struct(F.col("v").alias("src"), F.col("u").alias("dst")))
        return self.edges.select(F.explode(both).alias("a"), "t").select("a.src", "a.dst", "t")

    @cached_property
    def static(self) -> DataFrame:
        """v, nbr: the graph without times, both directions."""
        return self.arcs.select(F.col("src").alias("v"), F.col("dst").alias("nbr")).distinct()

    @cached_property
    def occurrences(self) -> DataFrame:
        """v, t, n_out: arcs that leave a vertex at a time."""
        return self.arcs.groupBy(F.col("src").alias("v"), "t").agg(F.count("*").alias("n_out"))

    def induced(self, vertices: DataFrame) -> TemporalGraph:
        """Edges with both ends in vertices (first column)."""
        s = vertices.select(F.col(vertices.columns[0]).alias("__s")).distinct()
        return TemporalGraph(self.edges.join(s, F.col("u") == F.col("__s"), "left_semi").join(s, F.col("v") == F.col("__s"), "left_semi"))

    def neighbours(self, vertices: DataFrame) -> DataFrame:
        """v, neighbours: within a vertex set."""
        return self.induced(vertices).static.groupBy("v").agg(F.array_sort(F.collect_set("nbr")).alias("neighbours"))

    def out_arcs(self, v: int) -> DataFrame:
        return self.arcs.where(F.col("src") == v)

    def in_arcs(self, v: int) -> DataFrame:
        return self.arcs.where(F.col("dst") == v)

    def vertex_stats(self) -> DataFrame:
        """v, t_count, temporal_degree, degree: one shuffle of partial aggregates."""
        pairs = self.arcs.groupBy("src", "dst").agg(F.count("*").alias("n"))
        degree = pairs.groupBy(F.col("src").alias("v")).agg(F.sum("n").alias("temporal_degree"), F.count("*").alias("degree"))
        return degree.join(self.occurrences.groupBy("v").agg(F.count("*").alias("t_count")), "v").select("v", "t_count", "temporal_degree", "degree")

    def describe(self) -> DataFrame:
        """n, m, m_static, t_max, n_times: one row."""
        s = self.vertex_stats().agg(F.count("*").alias("n"), (F.sum("temporal_degree") / 2).cast("bigint").alias("m"), (F.sum("degree") / 2).cast("bigint").alias("m_static"), F.max("t_count").alias("t_max"))
        return s.crossJoin(self.edges.agg(F.count_distinct("t").alias("n_times")))  # two single rows

    def slice(self, since: int | None = None, until: int | None = None) -> TemporalGraph:
        """Times since <= t < until; reaches the scan as a filter, or a partition filter of a stored graph."""
        e = self.edges
        e = e if since is None else e.where(F.col("t") >= since)
        return TemporalGraph(e if until is None else e.where(F.col("t") < until))

    def coarsen(self, step: int) -> TemporalGraph:
        """Times in steps; edges that become equal merge."""
        return TemporalGraph(self.edges.select("u", "v", F.floor(F.col("t") / step).alias("t")).distinct())

    def sample(self, share: int, by: str = "vertex", seed: int = 0) -> TemporalGraph:
        """About share percent of vertices (edges between them) or of edges, by a hash that SQL can repeat."""
        inside = lambda x: portable_hash(x + seed) % 100 < share
        if by == "edge":
            return TemporalGraph(self.edges.where(inside((F.col("u") * 31 + F.col("v")) * 31 + F.col("t"))))
        return TemporalGraph(self.edges.where(inside(F.col("u")) & inside(F.col("v"))))

    @property
    def vertices(self) -> DataFrame:
        """v."""
        return self.static.select("v").distinct()

    def stream_order(self) -> DataFrame:
        """The edge stream: ascending times."""
        return self.edges.orderBy("t", "u", "v")


class SlotGraph(TemporalGraph):
    """All who share a time meet: given by its members (v, t), distinct. Edges grow with the square of a time's members, so what can do
    without them asks for slots; once settled, they are written when first asked for."""

    def __init__(self, slots: DataFrame, *, keep: bool = False):
        self.slots, self._keep = slots, keep

    @property
    def spark(self) -> SparkSession:
        return self.slots.sparkSession

    @cached_property
    def edges(self) -> DataFrame:
        a, b = self.slots.select(F.col("v").alias("u"), "t"), self.slots.select("v", F.col("t").alias("s"))
        pairs = a.join(b, (F.col("t") == F.col("s")) & (F.col("u") < F.col("v"))).select("u", "v", "t")  # members are distinct, so pairs are
        return settle(pairs) if self._keep else pairs

    def settled(self) -> SlotGraph:
        return self if self._keep else SlotGraph(settle(self.slots), keep=True)

    @cached_property
    def static(self) -> DataFrame:
        """From the slots in tasks that hold them all; from the edges where these are too many."""
        from proxcore import compact

        found = compact.static(self)
        return self.arcs.select(F.col("src").alias("v"), F.col("dst").alias("nbr")).distinct() if found is None else found

    @cached_property
    def occurrences(self) -> DataFrame:
        sizes = self.slots.groupBy("t").agg((F.count("*") - 1).alias("n_out")).where("n_out > 0")
        return self.slots.join(sizes, "t").select("v", "t", "n_out")

    @property
    def vertices(self) -> DataFrame:
        return self.occurrences.select("v").distinct()

"""Connected components of an edge table by hooking and pointer jumping; all state stays in tables.

In a phase each node hooks to its least smaller neighbour, pointers are followed in doubled steps to the least node of each
tree, and the edges that weren't used to hook go on between these least nodes. A step is one shuffled join, whose rows are a
few numbers; a node that many others point to is a large key on one side only, which AQE's skew join splits.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxcore.llm.common import keep


def _ordered(edges: DataFrame) -> DataFrame:
    return edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))


def _hooked(edges: DataFrame) -> DataFrame:
    """node, first (what it hooked to), up (the least node of its tree): the larger nodes of edges (a > b)."""
    up = keep(edges.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("first")).withColumn("up", F.col("first")))
    while True:
        ahead = up.select(F.col("node").alias("of"), F.col("up").alias("next"))
        up = keep(up.select("node", "first", "up").join(ahead, F.col("up") == F.col("of"), "left").select("node", "first", F.coalesce("next", "up").alias("up"), F.col("next").isNotNull().alias("moved")))
        if up.where("moved").isEmpty():
            return up.drop("moved")


def components(edges: DataFrame) -> DataFrame:
    """node, root: the least node of its component, for every node of the edges (a, b: bigint, not null) between two nodes."""
    left, roots = _ordered(edges), None
    while True:
        up = _hooked(left)
        if roots is None:
            roots = up.select("node", F.col("up").alias("root"))
        else:
            further = up.select(F.col("node").alias("of"), "up")
            roots = keep(roots.join(further, F.col("root") == F.col("of"), "left").select("node", F.coalesce("up", "root").alias("root")).unionByName(up.select("node", F.col("up").alias("root"))))
        unused = keep(left.join(up, F.col("a") == F.col("node")).where("b <> first").select(F.col("up").alias("a"), "b"))
        if unused.isEmpty():
            return roots.unionByName(roots.select(F.col("root").alias("node"), "root").distinct())
        left = keep(_ordered(unused.join(up, F.col("b") == F.col("node"), "left").select("a", F.coalesce("up", "b").alias("b"))).distinct())

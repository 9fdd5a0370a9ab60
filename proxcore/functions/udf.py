"""Vectorised and grouped functions around the kernels. Native expressions come first: these are for decays that SQL lacks,
and for running a sequential method per group from SQL."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from proxcore import compact, kernels
from proxcore.slots import Slots

#: Arcs of a linear system that is solved as a dense one.
MOST_DENSE = 4_000


def decay_udf(f: Callable[[pd.Series], pd.Series]):  # noqa: ANN201
    """A decay of one's own, over whole batches of waits."""

    @F.pandas_udf("double")
    def decay(dt: pd.Series) -> pd.Series:
        return f(dt.astype("float64")).astype("float64")

    return decay


@F.pandas_udf(T.DoubleType())
def smallest(rho: pd.Series) -> float:
    """The least value of a group."""
    return float(rho.min()) if len(rho) else float("nan")


def communities_by_graph(edges: DataFrame, queries: DataFrame, alpha: float = 0.2) -> DataFrame:
    """graph, q, v, beta for many small graphs at a time: edges (graph, u, v, t), queries (graph, q), one task for each graph."""

    def run(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        rows: list[tuple] = []
        if len(left) and len(right):
            walks = kernels.Walks(zip(left["u"].tolist(), left["v"].tolist(), left["t"].tolist(), strict=True))
            adj = kernels.adjacency((u, v) for u, v, _ in walks.edges)
            for q in sorted(set(right["q"].tolist())):
                beta, members = kernels.exact_peel(adj, walks.stream(q, alpha), q)
                rows += [(int(left["graph"].iloc[0]), q, v, float(beta)) for v in sorted(members)]
        return pd.DataFrame(rows, columns=["graph", "q", "v", "beta"])

    return edges.groupBy("graph").cogroup(queries.groupBy("graph")).applyInPandas(run, "graph bigint, q bigint, v bigint, beta double")


def _meetings(slots: pd.DataFrame) -> pd.DataFrame:
    """u, v, t of a graph by slots (v, t)."""
    both = slots.rename(columns={"v": "u"}).merge(slots, on="t")
    return both[both["u"] < both["v"]]


def proximity_by_graph(edges: DataFrame, queries: DataFrame, alpha: float = 0.2, method: str = "stream") -> DataFrame:
    """graph, q, v, prox by the sequential methods: one pass over the edge stream, or the dense linear system (which holds all
    pairs of arcs), for many small graphs at a time: edges (graph, u, v, t), queries (graph, q); a task for each query. The system is
    triangular, for arcs feed later ones alone, so beyond MOST_DENSE arcs it is solved by substitution in order of time.
    In place of edges, slots (graph, v, t) whose members all meet: these are sent to the tasks, and beyond MOST_DENSE arcs the
    substitution goes by them (`slots`), so that no table lists the edges."""
    by_slots = "u" not in edges.columns

    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        graph, q = int(key[0]), int(key[1])
        if by_slots:
            pdf = pdf[["v", "t"]].drop_duplicates()
            n = pdf["t"].value_counts()
        n_arcs = int((n * (n - 1)).sum()) if by_slots else 2 * len(pdf)
        if method == "dense" and n_arcs > MOST_DENSE:
            a = (Slots if by_slots else compact.Arrays)(*(pdf[c].to_numpy(np.int64) for c in (("v", "t") if by_slots else ("u", "v", "t"))))
            if (k := a.at(q)) is None:
                return pd.DataFrame([], columns=["graph", "q", "v", "prox"])
            x = a.proximity([k], alpha)[:, 0]
            has = np.flatnonzero(x)
            return pd.DataFrame({"graph": graph, "q": q, "v": a.ids[has], "prox": x[has]})
        pdf = _meetings(pdf) if by_slots else pdf
        walks = kernels.Walks(zip(pdf["u"].tolist(), pdf["v"].tolist(), pdf["t"].tolist(), strict=True))
        scores = walks.stream(q, alpha) if method == "stream" else walks.dense(q, alpha)
        return pd.DataFrame([(graph, q, v, float(x)) for v, x in sorted(scores.items()) if x], columns=["graph", "q", "v", "prox"])

    spread = edges.join(queries.select("graph", "q").distinct(), "graph").select("graph", "q", *(c for c in ("u", "v", "t") if c in edges.columns))
    return spread.groupBy("graph", "q").applyInPandas(run, "graph bigint, q bigint, v bigint, prox double")


@F.udtf(returnType=T.StructType([T.StructField(c, T.LongType()) for c in ("v", "t", "wait")]))
class LaterNeighbours:
    """later_neighbours(since => 3, row => TABLE(arcs) PARTITION BY src ORDER BY t): those a walk that arrives at `since` may go to."""

    def eval(self, row, since: int) -> Iterator[tuple[int, int, int]]:  # noqa: ANN001
        if row["t"] > since:
            yield row["dst"], row["t"], row["t"] - since


def register(spark: SparkSession) -> None:
    spark.udtf.register("later_neighbours", LaterNeighbours)
    spark.udf.register("smallest_value", smallest)
    spark.udf.register("hyperbolic_decay", decay_udf(lambda dt: 1 / (1 + dt)))


def macro(spark: SparkSession, name: str, df: DataFrame) -> None:
    """A method's result as a view; iterative methods can't run inside a SQL function."""
    df.createOrReplaceTempView(name)

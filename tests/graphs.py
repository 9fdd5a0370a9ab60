"""Small graphs that tests share."""

import random

from proxcore.graph import TemporalGraph

BASIC = [(1, 2, 1), (1, 3, 2), (2, 3, 3), (2, 4, 3), (3, 4, 4), (3, 5, 5), (4, 5, 6)]
STOPS = [(1, 2, 1), (3, 4, 1), (2, 4, 2), (1, 4, 3), (3, 4, 4)]
TIES = [(3, 4, 1), (1, 3, 2), (3, 4, 3), (2, 4, 4)]


def random_edges(seed: int, n: int = 8, m: int = 16, times: int = 6) -> list[tuple[int, int, int]]:
    r = random.Random(seed)
    out = set()
    while len(out) < m:
        u, v = sorted(r.sample(range(n), 2))
        out.add((u, v, r.randrange(times)))
    return sorted(out)


def graph(spark, edges) -> TemporalGraph:
    return TemporalGraph.from_edges(spark.createDataFrame(edges, "u bigint, v bigint, t bigint"))


def as_dict(rows, q=None) -> dict[int, float]:
    return {r["v"]: r["prox"] for r in rows if q is None or r["q"] == q}

"""The methods in a task against the distributed ones and the sequential kernels."""

import numpy as np
import pytest

from proxcore import compact, exact, local, metrics
from proxcore import kernels as K
from proxcore import proximity as P
from proxcore.baselines import static
from tests.graphs import BASIC, STOPS, TIES, graph, random_edges

GRAPHS = [BASIC, STOPS, TIES, *(random_edges(s, 9, 18) for s in range(40))]


def arrays(edges, decay="reciprocal"):
    return compact.Arrays(*(np.array(c) for c in zip(*edges, strict=True)), decay)


@pytest.mark.parametrize("decay", ["reciprocal", "log", ("exp", 0.3)])
def test_proximity_and_exact_are_the_kernels(decay):
    for edges in GRAPHS:
        a, w, adj = arrays(edges, decay), K.Walks(edges, decay), K.adjacency((u, v) for u, v, _ in edges)
        prox = a.proximity(list(range(a.n)), 0.2)
        for k, q in enumerate(a.ids.tolist()):
            true = w.stream(q, 0.2)
            assert all(abs(prox[j, k] - true.get(v, 0)) < 1e-12 for j, v in enumerate(a.ids.tolist()))
            units = np.floor(prox[:, k] * 10**9 + 0.5).astype(np.int64)
            beta, members = a.best_core(units, k)
            assert (beta, set(a.ids[members].tolist())) == K.exact_peel(adj, dict(zip(a.ids.tolist(), units.tolist(), strict=True)), q)


@pytest.mark.parametrize("prune,stop,anchor", [(True, True, "max"), (False, False, "query")])
def test_local_holds_its_certificate(prune, stop, anchor):
    for edges in GRAPHS:
        a, adj = arrays(edges), K.adjacency((u, v) for u, v, _ in edges)
        prox = a.proximity(list(range(a.n)), 0.2)
        for k in range(a.n):
            weight = dict(zip(a.ids.tolist(), prox[:, k].tolist(), strict=True))
            beta, best = K.exact_peel(adj, weight, int(a.ids[k]))
            members, lower, facts = a.expand(k, 0.2, prune=prune, stop=stop)
            assert (lower <= prox[:, k] + 1e-12).all() and (prox[:, k] <= lower + facts["residue"] + 1e-12).all()
            assert beta <= 1e-9 or best <= set(a.ids[members].tolist())
            eps, found = a.shrink(members, lower, facts["residue"], k, anchor=anchor)
            got = K.smallest(adj, weight, set(a.ids[found].tolist()))
            assert k in found and got <= beta + 1e-9 and (eps == np.inf or beta <= eps * got + 1e-9)


def rows(df, *columns):
    return sorted(tuple(round(r[c], 9) if isinstance(r[c], float) else r[c] for c in columns) for r in df.collect())


@pytest.mark.parametrize("seed", [3, 4])
def test_tasks_and_distributed_methods_agree(spark, seed):
    g = graph(spark, random_edges(seed, 12, 30)).settled()
    qs = [0, 3, 7, 99]
    assert rows(compact.proximity(g, qs), "q", "v", "prox") == rows(P.prox_hops(g, qs), "q", "v", "prox")
    assert rows(exact.exact_community(g, qs), "q", "v", "beta") == rows(exact.exact_community(g, qs, method="refine"), "q", "v", "beta")
    for weight in ("static", "temporal"):
        assert rows(static.static_core(g, qs, weight), "q", "v", "k") == rows(static.static_core(g, qs, weight, method="refine"), "q", "v", "k")
    assert rows(static.floor_kcore(g, qs, k=2), "q", "v", "floor") == rows(static.floor_kcore(g, qs, k=2, method="levels"), "q", "v", "floor")


def test_local_by_task_is_local_by_levels(spark):
    g = graph(spark, random_edges(5, 12, 26)).settled()
    columns = ("q", "v", "eps", "residue", "expanded", "visited", "reason")
    assert rows(local.local_community(g, [0, 3], method="task"), *columns) == rows(local.local_community(g, [0, 3], method="levels"), *columns)


def test_graphs_that_don_t_fit_take_the_distributed_way(spark, monkeypatch):
    monkeypatch.setattr(compact, "MOST_EDGES", 3)
    g = graph(spark, BASIC).settled()
    assert compact.ship(g) is None
    with pytest.raises(ValueError, match="distributed"):
        compact.proximity(g, [1])
    assert {r["v"] for r in exact.exact_community(g, [2]).collect()} == {2, 3, 4, 5}
    monkeypatch.setattr(compact, "MOST_EDGES", 10)
    monkeypatch.setattr(compact, "MOST_PAIRS", 1)
    assert compact.ship(graph(spark, BASIC)) is None


def test_tasks_take_components_of_larger_graphs(spark, monkeypatch):
    """Two copies of a graph of 7 edges: with room for 8 a task holds the query's copy; with room for 3 the distributed way runs."""
    two = BASIC + [(u + 100, v + 100, t) for u, v, t in BASIC]
    g, one = graph(spark, two).settled(), graph(spark, BASIC).settled()
    want = [(q + 100, v + 100, x) for q, v, x in rows(static.floor_kcore(one, [2], k=2, method="task"), "q", "v", "floor")]
    own = {method: {r["v"] + 100 for r in local.local_community(one, [2], method=method).collect()} for method in ("task", "queue")}
    monkeypatch.setattr(compact, "MOST_EDGES", 8)
    monkeypatch.setattr(local, "IN_TASK", 8)
    assert rows(compact.near(g, [102]).edges, "u", "v", "t") == sorted((u + 100, v + 100, t) for u, v, t in BASIC)
    assert rows(static.floor_kcore(g, [102], k=2, method="task"), "q", "v", "floor") == want
    for method in ("task", "queue"):
        assert {r["v"] for r in local.local_community(g, [102], method=method).collect()} == own[method]
    assert metrics.array_bytes(g, [102]).count() == 3
    monkeypatch.setattr(compact, "MOST_EDGES", 3)
    monkeypatch.setattr(local, "IN_TASK", 3)
    h = graph(spark, two).settled()
    with pytest.warns(UserWarning, match="distributed"):
        assert compact.or_distributed(lambda: local._by_task(h, [102], 0.2, "reciprocal", True, True, "max")) is None
        assert rows(static.floor_kcore(h, [102], k=2, method="task"), "q", "v", "floor") == want


def test_bytes_of_arrays_too_large_to_send(spark, monkeypatch):
    """One task makes them, or their lengths are counted: the same numbers."""
    edges = random_edges(5, 12, 40)
    got = lambda qs: sorted(map(tuple, metrics.array_bytes(graph(spark, edges).settled(), qs).collect()))
    want, none = got([0, 3, 99]), got([99])
    assert len(want) == 3 and none == [] and want[1][0] == "graph" and want[1][1] == arrays(edges).nbytes()
    monkeypatch.setattr(compact, "MOST_EDGES", 3)
    with pytest.warns(UserWarning, match="distributed"):
        assert got([0, 3, 99]) == want  # TooLarge before
        monkeypatch.setattr(compact, "MOST_BYTES", 100)
        assert got([0, 3, 99]) == want and got([99]) == none


def test_an_empty_graph_has_no_communities(spark):
    g = graph(spark, BASIC)
    empty = type(g)(g.edges.where("t > 100"))
    assert exact.exact_community(empty, [1]).count() == 0 and static.floor_kcore(empty, [1]).count() == 0

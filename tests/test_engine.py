"""Distributed methods against the kernels."""

import math
from itertools import combinations

import pytest
from pyspark.sql import functions as F

from proxcore import cores, exact, local, metrics, transitions
from proxcore import drift as D
from proxcore import kernels as K
from proxcore import proximity as P
from proxcore.baselines import heuristics, static, temporal
from proxcore.graph import TemporalGraph
from tests.graphs import BASIC, as_dict, graph, random_edges


def near(a, b, eps=1e-8):
    return all(abs(a.get(k, 0) - b.get(k, 0)) < eps for k in set(a) | set(b))


def test_repeats_reversals_and_loops_don_t_count(spark):
    messy = [*BASIC, (2, 1, 1), (5, 4, 6), (3, 3, 3)]
    assert sorted(map(tuple, graph(spark, messy).edges.collect())) == sorted(BASIC)
    d = graph(spark, BASIC).describe().first()
    assert (d["n"], d["m"], d["m_static"], d["t_max"], d["n_times"]) == (5, 7, 7, 4, 6)


@pytest.mark.parametrize("seed", [1, 2])
def test_all_ways_to_proximity_agree(spark, seed):
    edges = random_edges(seed, 9, 18)
    g, w = graph(spark, edges).settled(), K.Walks(edges)
    qs = sorted(w.times)[:2]
    hops = P.prox_hops(g, qs).collect()
    slabs = P.prox_slabs(g, qs, slab=2).collect()
    power = P.prox_power(g, qs, tol=1e-11).collect()
    walks = P.prox_walks(g, qs, depth=4).collect()
    for q in qs:
        true = w.dense(q, 0.2)
        assert near(as_dict(hops, q), true) and near(as_dict(slabs, q), true) and near(as_dict(power, q), true)
        low = as_dict(walks, q)
        assert all(low.get(v, 0) <= x + 1e-9 for v, x in true.items()) and 1 - sum(low.values()) <= 0.8**4 + 1e-9
    assert all(abs(r["mass"] - 1) < 1e-9 for r in P.check_mass(P.prox_hops(g, qs)).collect())
    sampled = as_dict(P.prox_sampled(g, [qs[0]], walks=2000).collect(), qs[0])
    assert near(sampled, w.dense(qs[0], 0.2), 0.06)


def test_push_keeps_the_invariant(spark):
    edges = random_edges(5, 9, 20)
    g, w = graph(spark, edges).settled(), K.Walks(edges)
    q = edges[0][0]
    lower, residue = P_push(g, q)
    true = w.dense(q, 0.2)
    low = {r["v"]: r["low"] for r in lower.collect()}
    left = residue.agg(F.sum("r")).first()[0] or 0.0
    assert all(low.get(v, 0) <= x + 1e-9 <= low.get(v, 0) + left + 2e-9 for v, x in true.items())
    assert abs(sum(low.values()) + left - 1) < 1e-9


def P_push(g, q):
    return local.push_temporal(g, [q], least=0.02)


def test_transitions(spark):
    g = graph(spark, random_edges(3, 8, 18))
    for decay in ("reciprocal", "log", ("exp", 0.4)):
        assert all(abs(r["total"] - 1) < 1e-9 for r in transitions.check_stochastic(g, decay).collect())
    a = {(r["v"], r["t"]): r["norm"] for r in transitions.norms(g, ("exp", 0.4)).collect()}
    b = {(r["v"], r["t"]): r["norm"] for r in transitions.norms_exponential(g, 0.4).collect()}
    assert a.keys() == b.keys() and all((a[k] is None) == (b[k] is None) and (a[k] is None or abs(a[k] - b[k]) < 1e-9) for k in a)


@pytest.mark.parametrize("method", ["refine", "peel", "bisect"])
def test_exact_methods(spark, method):
    edges = random_edges(11, 9, 20)
    g, w = graph(spark, edges).settled(), K.Walks(edges)
    adj = K.adjacency((u, v) for u, v, _ in edges)
    qs = sorted(adj)[: 2 if method == "bisect" else 4]
    got = exact.exact_community(g, qs, unit=10**5 if method == "bisect" else 10**9, method=method).collect()
    for q in qs:
        unit = 10**5 if method == "bisect" else 10**9
        beta, members = K.exact_brute(adj, {v: round(x * unit) for v, x in w.dense(q, 0.2).items()}, q)
        assert {r["v"] for r in got if r["q"] == q} == members
        assert all(abs(r["beta"] * unit - beta) < 1e-6 for r in got if r["q"] == q)


def test_a_query_without_edges_and_components(spark):
    g = graph(spark, [*BASIC, (10, 11, 1), (11, 12, 1)])
    assert exact.exact_community(g, [99]).count() == 0
    assert {r["v"] for r in exact.exact_community(g, [10]).collect()} <= {10, 11, 12}
    assert exact.exact_community_multi(g, [1, 10]).count() == 0
    labels = {r["v"]: r["label"] for r in cores.connected_components(g.static).collect()}
    assert labels == {1: 1, 2: 1, 3: 1, 4: 1, 5: 1, 10: 10, 11: 10, 12: 10}


def test_exact_for_two_queries_is_brute_force(spark):
    edges = random_edges(21, 7, 13)
    g, w = graph(spark, edges), K.Walks(edges)
    adj = K.adjacency((u, v) for u, v, _ in edges)
    qs = sorted(adj)[:2]
    mean = {v: (w.dense(qs[0], 0.2).get(v, 0) + w.dense(qs[1], 0.2).get(v, 0)) / 2 for v in adj}
    weight = {v: round(x * 10**9) for v, x in mean.items()}
    best = (-1, 0, set())
    for k in range(2, len(adj) + 1):
        for s in map(set, combinations(sorted(adj), k)):
            if set(qs) <= s and K.connected(adj, s, qs[0]) == s:
                best = max(best, (K.smallest(adj, weight, s), len(s), s), key=lambda x: x[:2])
    assert {r["v"] for r in exact.exact_community_multi(g, qs).collect()} == best[2]


def test_local_levels_hold_their_certificate(spark):
    edges = random_edges(31, 14, 30)
    g, w = graph(spark, edges).settled(), K.Walks(edges)
    adj = K.adjacency((u, v) for u, v, _ in edges)
    qs = sorted(adj)[:2]
    rows = local.local_community(g, qs, method="levels").collect()
    for q in qs:
        members, prox = {r["v"] for r in rows if r["q"] == q}, w.dense(q, 0.2)
        beta, _ = K.exact_peel(adj, prox, q)
        eps = next(r["eps"] for r in rows if r["q"] == q)
        got = K.smallest(adj, prox, members)
        assert q in members and got <= beta + 1e-9 and (eps == math.inf or beta <= eps * got + 1e-9)
    tasks = local.local_community(g, qs, method="queue").collect()
    assert {r["q"] for r in tasks} == set(qs)
    both = local.local_community_multi(g, qs, method="levels").collect()
    assert {r["v"]: round(r["eps"], 9) for r in both} == {r["v"]: round(r["eps"], 9) for r in local.local_community_multi(g, qs, method="task").collect()}
    assert not both or set(qs) <= {r["v"] for r in both}


def test_core_numbers_and_monotony(spark):
    edges = random_edges(41, 9, 20)
    g, w = graph(spark, edges), K.Walks(edges)
    q = edges[0][0]
    weights = spark.createDataFrame([(q, v, round(x * 10**9)) for v, x in w.dense(q, 0.2).items()], "q bigint, v bigint, units bigint")
    levels = {r["v"]: r["core"] for r in cores.core_numbers(g.static, weights).collect()}
    for beta in {*levels.values()}:
        inside = cores.threshold_core(g.static, weights, spark.createDataFrame([(q, beta)], "q bigint, beta bigint")).collect()
        assert {r["v"] for r in inside} == {v for v, c in levels.items() if c >= beta}


def test_measures_of_the_basic_example(spark):
    g = graph(spark, BASIC)
    s = spark.createDataFrame([(2, v) for v in (2, 3, 4, 5)], "q bigint, v bigint")
    assert abs(metrics.temporal_density(g, s).first()["density"] - 10 / 48) < 1e-12
    assert metrics.temporal_conductance(g, s).first()["conductance"] == 1.0
    alone = spark.createDataFrame([(1, 1)], "q bigint, v bigint")
    assert metrics.temporal_density(g, alone).first()["density"] is None
    o = metrics.overlap_scores(s, spark.createDataFrame([(2, 2), (2, 3), (2, 9)], "q bigint, v bigint")).first()
    assert (o["precision"], o["recall"]) == (0.5, 2 / 3)


def test_static_baselines_are_brute_force(spark):
    edges = random_edges(51, 10, 26)
    g = graph(spark, edges).settled()
    adj = K.adjacency((u, v) for u, v, _ in edges)

    def core(k):
        s = set(adj)
        while bad := {v for v in s if len(adj[v] & s) < k}:
            s -= bad
        return s

    for q in sorted(adj)[:3]:
        k = max(k for k in range(10) if q in core(k))
        got = static.static_core(g, [q]).collect()
        assert {r["v"] for r in got} == K.connected(adj, core(k), q) and {r["k"] for r in got} == {k}
    pairs = {(u, v) for u, v, _ in edges}

    def truss(k):
        s = set(pairs)
        while bad := {(u, v) for u, v in s if sum((min(u, x), max(u, x)) in s and (min(v, x), max(v, x)) in s for x in adj) < k - 2}:
            s -= bad
        return s

    for r in static.truss_numbers(g.static).collect():
        assert (r["u"], r["v"]) in truss(r["k"]) and (r["u"], r["v"]) not in truss(r["k"] + 1)
    assert static.triangles(g.static).count() == sum(1 for t in combinations(sorted(adj), 3) if all(b in adj[a] for a, b in combinations(t, 2)))


def test_sweep_cut_takes_the_best_prefix(spark):
    edges = random_edges(61, 10, 22)
    g = graph(spark, edges).settled()
    adj = K.adjacency((u, v) for u, v, _ in edges)
    q = edges[0][0]
    scores = {r["v"]: r["reserve"] for r in P.push_static(g, [q]).collect() if r["reserve"] > 0}
    order = sorted(scores, key=lambda v: (-round(scores[v] / len(adj[v]), 12), v))
    best = []
    for k in range(1, len(order) + 1):
        s = set(order[:k])
        cut, vol = sum(len(adj[v] - s) for v in s), sum(len(adj[v]) for v in s)
        rest = sum(map(len, adj.values())) - vol
        if q in s and min(vol, rest):
            best.append(cut / min(vol, rest))
    got = static.sweep_cut(g, [q]).collect()
    assert abs(got[0]["conductance"] - min(best)) < 1e-12


def test_floor_kcore_is_brute_force(spark):
    edges = random_edges(71, 8, 22)
    g, w = graph(spark, edges).settled(), K.Walks(edges)
    adj = K.adjacency((u, v) for u, v, _ in edges)
    for q in sorted(adj)[:2]:
        prox = w.dense(q, 0.2)
        best = (-1.0, 0, set())
        for k in range(3, len(adj) + 1):
            for s in map(set, combinations(sorted(adj), k)):
                if q in s and min(len(adj[v] & s) for v in s) >= 2 and K.connected(adj, s, q) == s:
                    best = max(best, (round(min(prox.get(v, 0) for v in s), 12), len(s), s), key=lambda x: x[:2])
        got = static.floor_kcore(g, [q], k=2).collect()
        assert {r["v"] for r in got} == best[2]


def test_temporal_baselines(spark):
    clique = [(u, v, t) for u, v in combinations(range(1, 5), 2) for t in (1, 3, 5)]
    g = graph(spark, [*clique, (4, 5, 1), (5, 6, 2)]).settled()
    got = heuristics.periodic_clique(g, [1, 5], 3).collect()
    assert {r["v"] for r in got} == {1, 2, 3, 4} and {(r["start"], r["period"], r["exact"]) for r in got} == {(1, 2, True)}
    assert {r["v"] for r in temporal.interval_core(g, [1], (1, 1)).collect()} == {1, 2, 3, 4}
    assert {r["v"] for r in temporal.best_interval(g, [2], 1).collect()} == {1, 2, 3, 4}
    assert {r["v"] for r in temporal.persistent_core(g, [1, 6], theta=1, tau=3, k=3).collect()} == {1, 2, 3, 4}
    burst = temporal.density_burst(g, [1], 1).collect()
    assert {r["v"] for r in burst} == {1, 2, 3, 4} and abs(burst[0]["score"] - 1.5) < 1e-9
    assert 1 in {r["v"] for r in heuristics.inefficiency_community(g, [1]).collect()}


def test_the_connector_tries_every_neighbour_within_two_steps(spark):
    dense = [1, *range(51, 61)]
    edges = [(0, v, 1) for v in range(1, 61)] + [(u, v, 1) for u, v in combinations(dense, 2)] + [(v, 70, 1) for v in dense]
    got = heuristics.inefficiency_community(graph(spark, edges).settled(), [0], k=1).collect()
    assert {r["v"] for r in got} == {0, *dense, 70}


def test_drift(spark):
    # five vertices, seven edges at three times
    edges = [(1, 3, 2), (1, 4, 4), (3, 4, 2), (3, 5, 3), (4, 5, 3), (4, 6, 4), (5, 6, 2)]
    assert abs(D.burst_density(edges, frozenset({1, 3, 4, 5, 6})) - 7 / 15) < 1e-12
    far = [(1, 2, 1), *[(u, v, t) for u, v in combinations(range(3, 7), 2) for t in (5, 6)], (2, 3, 2)]
    weight = {1: 0.5, 2: 0.4, 3: 0.04, 4: 0.02, 5: 0.02, 6: 0.02}
    found, optimum = frozenset({1, 2}), frozenset({3, 4, 5, 6})
    assert D.free_rider(D.burst_density, far, optimum, found) and D.drifted(D.burst_density, far, weight, optimum, found) == {3, 4, 5, 6}
    for f in (D.interval_degree(frozenset({5})), D.persistent_size(1, 10, 1), D.periodic_clique(2), D.inefficiency()):
        assert isinstance(f(far, optimum), float)
    assert D.periodic_clique(2)(far, optimum) == 1.0
    f = D.smallest_biased(weight)
    assert f(far, found) >= 0


def test_samples_and_coarsening(spark):
    g = graph(spark, random_edges(81, 30, 120, 50))
    assert 0 < g.sample(50, "edge").edges.count() < 120 and g.coarsen(60).edges.select("t").distinct().count() == 1
    assert g.slice(10, 20).edges.where("t < 10 or t >= 20").count() == 0
    assert isinstance(g.stream_order().first()["t"], int) and isinstance(g, TemporalGraph)


def test_periodic_cliques_are_brute_force(spark):
    edges = random_edges(91, 8, 60, 7)
    g, have = graph(spark, edges).settled(), set(edges)
    names = sorted({x for e in edges for x in e[:2]})
    times = sorted({t for _, _, t in edges})
    for q in names[:3]:
        best = (0, 0, 0, ())
        for start in times:
            for period in range(1, 4):
                meets = lambda u, v, a=start, p=period: all((u, v, a + k * p) in have for k in range(3))
                for n in range(2, len(names) + 1):
                    for s in combinations(names, n):
                        if q in s and all(meets(u, v) for u, v in combinations(s, 2)):
                            best = max(best, (n, -start, -period, tuple(-x for x in s)))
        rows = heuristics.periodic_clique(g, [q], 3, 2).collect()
        want = set() if not best[0] else {(-x, -best[1], -best[2]) for x in best[3]}
        assert {(r["v"], r["start"], r["period"]) for r in rows} == want


def test_a_tree_joins_the_queries_of_the_temporal_searches(spark):
    g = graph(spark, [*BASIC, (5, 6, 6), (6, 7, 7), (20, 21, 1)]).settled()
    tree = {r["v"] for r in heuristics.query_tree(g.static, [1, 7]).collect()}
    assert tree == {1, 3, 5, 6, 7} and heuristics.query_tree(g.static, [1, 20]) is None
    assert {1, 7} <= {r["v"] for r in heuristics.inefficiency_community_multi(g, [1, 7]).collect()}
    assert heuristics.inefficiency_community_multi(g, [1, 20]).count() == 0
    clique = graph(spark, [(u, v, 1) for u, v in combinations(range(1, 5), 2)] + [(4, 5, 1)])
    assert {(r["v"], r["k"]) for r in temporal.interval_core_multi(clique, [1, 3], (1, 1)).collect()} == {(v, 3) for v in range(1, 5)}
    assert {(r["v"], r["k"]) for r in temporal.interval_core_multi(clique, [1, 5], (1, 1)).collect()} == {(v, 1) for v in range(1, 6)}

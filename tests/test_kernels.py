"""Sequential methods against definitions and brute force, and the cases where a literal procedure goes wrong."""

import math

import pytest

from proxcore import kernels as K
from tests.graphs import BASIC, STOPS, TIES, random_edges


def close(a, b, eps=1e-9):
    return all(abs(a.get(k, 0) - b.get(k, 0)) < eps for k in set(a) | set(b))


@pytest.mark.parametrize("seed", range(40))
@pytest.mark.parametrize("decay", ["reciprocal", "log", ("exp", 0.3)])
def test_stream_is_the_linear_system(seed, decay):
    w = K.Walks(random_edges(seed), decay)
    for q in list(w.times)[:3]:
        dense = w.dense(q, 0.2)
        assert close(w.stream(q, 0.2), dense)
        assert abs(sum(dense.values()) - 1) < 1e-9


def test_basic_example():
    w = K.Walks(BASIC)
    assert close(w.stream(1, 0.2), {2: 0.318181818, 3: 0.164, 4: 0.2608, 5: 0.257018182}, 1e-8)
    assert close(w.stream(3, 0.2), {1: 0.25, 2: 0.25, 4: 0.25, 5: 0.25})
    adj = K.adjacency((u, v) for u, v, _ in BASIC)
    for q, beta, members in ((1, 0.4248, {1, 2, 3, 4, 5}), (2, 0.504, {2, 3, 4, 5}), (3, 0.25, {1, 2, 3, 4, 5})):
        got = K.exact_peel(adj, w.stream(q, 0.2), q)
        assert got[1] == members and abs(got[0] - beta) < 1e-6


def test_time_scale_doesn_t_matter_for_reciprocal_decay():
    a, b = K.Walks(BASIC), K.Walks([(u, v, 24 * t) for u, v, t in BASIC])
    assert close(a.stream(2, 0.2), b.stream(2, 0.2))
    c, d = K.Walks(BASIC, ("exp", 0.5)), K.Walks([(u, v, 24 * t) for u, v, t in BASIC], ("exp", 0.5))
    assert not close(c.stream(2, 0.2), d.stream(2, 0.2))


def test_the_set_is_recorded_before_the_query_would_leave():
    w, adj = K.Walks(STOPS), K.adjacency((u, v) for u, v, _ in STOPS)
    beta, members = K.exact_peel(adj, w.stream(1, 0.2), 1)
    assert members == {1, 2, 4} and abs(beta - 0.28) < 1e-6


def test_ties_keep_the_larger_set():
    w, adj = K.Walks(TIES), K.adjacency((u, v) for u, v, _ in TIES)
    beta, members = K.exact_peel(adj, {v: round(x, 9) for v, x in w.stream(1, 0.2).items()}, 1)
    assert members == {1, 2, 3, 4} and abs(beta - 0.16) < 1e-6


@pytest.mark.parametrize("seed", range(60))
def test_peel_is_brute_force(seed):
    edges = random_edges(seed, 7, 13)
    w, adj = K.Walks(edges), K.adjacency((u, v) for u, v, _ in edges)
    for q in list(adj)[:2]:
        weight = {v: round(x * 10**9) for v, x in w.stream(q, 0.2).items()}
        assert K.exact_peel(adj, weight, q) == K.exact_brute(adj, weight, q)


def test_a_dangling_arc_banks_its_whole_residue():
    w = K.Walks([(1, 2, 1), (2, 3, 2)])
    x = K.expand(w, 1, 0.2, least=1e-9, prune=False, stop=False)
    assert abs(x["lower"][2] - 0.2) < 1e-12 and abs(x["lower"][3] - 0.8) < 1e-12 and x["residue"] < 1e-12


@pytest.mark.parametrize("seed", range(40))
@pytest.mark.parametrize(("prune", "stop"), [(True, True), (True, False), (False, True), (False, False)])
def test_bounds_and_certificates_hold(seed, prune, stop):
    edges = random_edges(seed, 12, 26)
    w, adj = K.Walks(edges), K.adjacency((u, v) for u, v, _ in edges)
    q = edges[0][0]
    prox = w.dense(q, 0.2)
    x = K.expand(w, q, 0.2, prune=prune, stop=stop)
    beta, best = K.exact_peel(adj, prox, q)
    for v in x["members"]:
        low = sum(x["lower"].get(u, 0) for u in adj[v] & x["members"])
        true = sum(prox.get(u, 0) for u in adj[v] & x["members"])
        assert low - 1e-9 <= true <= low + x["residue"] + 1e-9
    if beta > 0:
        assert best <= x["members"]
    eps, found = K.shrink(adj, x["members"], x["lower"], x["residue"], q)
    got = K.smallest(adj, prox, found)
    assert q in found and K.connected(adj, found, q) == found
    assert got <= beta + 1e-9 and (eps == math.inf or beta <= eps * got + 1e-9)


def test_degenerate_graphs():
    one = K.Walks([(1, 2, 5)])
    assert close(one.stream(1, 0.2), {2: 1.0})
    assert K.exact_peel(K.adjacency([(1, 2)]), one.stream(1, 0.2), 1) == (0, {1, 2})
    assert one.stream(9, 0.2) == {} and one.dense(9, 0.2) == {}
    same = K.Walks([(1, 2, 3), (1, 3, 3), (2, 3, 3)])
    assert close(same.stream(1, 0.2), {2: 0.5, 3: 0.5})
    assert K.clean([(2, 1, 1), (1, 2, 1), (3, 3, 1)]) == [(1, 2, 1)]

"""Graphs by slots against the same graphs by edges."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from proxcore import compact, cores, exact, local, metrics
from proxcore import proximity as P
from proxcore.baselines import temporal
from proxcore.catalog import community, structure, surroundings
from proxcore.functions import udf
from proxcore.graph import SlotGraph, TemporalGraph
from proxcore.runtime import settle
from proxcore.slots import Slots
from proxcore.sources.views import VIEWS
from tests.graphs import random_edges

SF = "/root/testdata/sf0.001"
rows = lambda df: sorted(map(tuple, df.collect()))


def members(seed):
    r = random.Random(seed)
    return sorted({(r.randrange(9), r.randrange(7)) for _ in range(r.randrange(6, 26))})


@pytest.mark.parametrize("listed", [True, False])
def test_slots_are_the_arrays_of_their_edges(listed, monkeypatch):
    if not listed:
        monkeypatch.setattr("proxcore.slots.MOST_LISTED", -1)
    for seed in range(40):
        own = members(seed)
        edges = [(u, v, t) for u, t in own for v, s in own if s == t and u < v]
        if not edges:
            continue
        a, b = compact.Arrays(*np.array(edges).T), Slots(*np.array(own).T)
        assert (a.ids == b.ids).all() and a.m == b.m
        prox = a.proximity(list(range(a.n)), 0.2)
        assert abs(prox - b.proximity(list(range(a.n)), 0.2)).max() < 1e-12
        for q in range(a.n):
            units = np.floor(prox[:, q] * 10**9 + 0.5).astype(np.int64)
            (x, found), (y, same) = a.best_core(units, q), b.best_core(units, q)
            assert x == y and (found == same).all()
            assert [a.best_core(units, k)[0] for k in range(a.n)] == b.core_numbers(units).tolist()
            for how in ({}, {"prune": False, "stop": False}):
                (m, low, facts), (n, other, told) = a.expand(q, 0.2, **how), b.expand(q, 0.2, **how)
                assert (m == n).all() and abs(low - other).max() < 1e-12 and facts["reason"] == told["reason"]
                assert (a.shrink(m, low, facts["residue"], q)[1] == b.shrink(n, other, told["residue"], q)[1]).all()


@pytest.fixture
def no_edges(monkeypatch):
    """A graph by slots may not list its edges: these grow with the square of a slot."""

    def listed(_):
        raise AssertionError("edges were listed")

    community._base.cache_clear()
    monkeypatch.setattr(SlotGraph, "edges", property(listed))
    yield
    community._base.cache_clear()


@pytest.mark.parametrize("name", ["prox_meet10", "core_numbers_meet10", "exact_meet10", "local_task_dense", "stream_follow", "persistent_core"])
def test_queries_over_meetings_list_no_edges(spark, no_edges, name):
    assert (structure.QUERIES | community.QUERIES | surroundings.QUERIES)[name](spark, SF).count() >= 0


def test_both_forms_agree(spark):
    own = members(3)
    g = SlotGraph(spark.createDataFrame(own, "v bigint, t bigint")).settled()
    h = TemporalGraph(g.edges).settled()
    assert rows(g.vertices) == rows(h.vertices) and rows(g.occurrences) == rows(h.occurrences)
    q = h.vertices.select("v").withColumnRenamed("v", "q")
    weights = settle(cores.in_units(P.prox_hops(h, q)))
    assert rows(cores.in_units(P.prox(g, q))) == rows(weights)
    assert rows(compact.core_numbers(g, weights)) == rows(cores.core_numbers(h.static, weights))
    found = settle(exact.from_weights(h.static, weights, q))
    assert rows(compact.from_weights(g, weights, q)) == rows(found)
    assert rows(compact.smallest_degree(g, weights, found)) == rows(metrics.min_biased_degree(h.static, weights, found))
    assert rows(cores.component(g.slots, found)) == rows(cores.component(h.static, found))
    assert rows(local.local_community(g, q).select("q", "v")) == rows(local.local_community(h, q).select("q", "v"))


@pytest.mark.parametrize("how", [(3, 2, 2), (2, 1, 1), (4, 3, 2)])
def test_persistent_cores_by_slots(spark, how):
    g = VIEWS["meet"](spark, SF).settled()
    h = TemporalGraph(g.edges)
    q = structure.pick(g, 5)
    assert rows(temporal.persistent_core(g, q, *how)) == rows(temporal.persistent_core(h, q, *how))


def test_large_linear_systems_are_solved_by_substitution(spark, monkeypatch):
    edges = spark.createDataFrame([(0, *e) for e in random_edges(4, 9, 18)], "graph bigint, u bigint, v bigint, t bigint")
    queries = spark.createDataFrame([(0, 1), (0, 2), (0, 99)], "graph bigint, q bigint")
    prox = lambda: rows(udf.proximity_by_graph(edges, queries, method="dense").selectExpr("q", "v", "round(prox, 9) AS prox").where("prox > 0"))
    dense = prox()
    monkeypatch.setattr(udf, "MOST_DENSE", 0)
    assert dense and prox() == dense


def test_a_large_graph_gives_a_task_the_queries_components(spark, monkeypatch):
    """auto took the distributed way for all of a graph beyond a task, although the walks stay in a small component."""
    small, far = random_edges(4, 9, 18), [(u + 100, v + 100, t) for u, v, t in random_edges(5, 40, 90)]
    g = TemporalGraph.from_edges(spark.createDataFrame(small + far, "u bigint, v bigint, t bigint")).settled()
    want = rows(exact.exact_community(TemporalGraph.from_edges(spark.createDataFrame(small, "u bigint, v bigint, t bigint")), [1, 2]))
    monkeypatch.setattr(compact, "MOST_EDGES", 30)
    monkeypatch.setattr(exact, "prox_hops", None)
    assert compact.ship(g) is None and want and rows(exact.exact_community(g, [1, 2])) == want
    assert compact.near(g, [1, 2]) is compact.near(g, [2, 1])


def test_certificate_over_meetings_lists_no_edges(spark, no_edges):
    """F8: the level-wise method listed the edges of every slot."""
    got = rows(community.QUERIES["local_certificate_dense"](spark, SF))
    assert len(got) == 2 and all(r[1:] == (True, True, True) for r in got)


def test_certificate_by_slots_can_fail(spark):
    g = SlotGraph(spark.createDataFrame(members(3), "v bigint, t bigint")).settled()
    q = settle(g.vertices.selectExpr("v as q"))
    prox = settle(compact.proximity(g, q))
    weights = settle(cores.in_units(prox))
    assert {r[1:] for r in rows(compact.certificate(g, prox, weights, q))} == {(True, True, True)}
    assert any(not r[1] for r in rows(compact.certificate(g, prox.selectExpr("q", "v", "prox / 2 as prox"), weights, q)))


@pytest.mark.parametrize("most", [10**6, 0])
def test_neighbours_over_meetings_list_no_edges(spark, no_edges, monkeypatch, most):
    """all temporal edges were listed and then made distinct."""
    monkeypatch.setattr(compact, "BATCH_ROWS", 3)
    monkeypatch.setattr("proxcore.slots.MOST_LISTED", most)
    own = [*members(5), (77, 99)]  # the last meets nobody
    want = sorted({(u, v) for u, t in own for v, s in own if s == t and u != v})
    assert rows(SlotGraph(spark.createDataFrame(own, "v bigint, t bigint")).static) == want
    assert structure.QUERIES["static_meet"](spark, SF).count() > 0


def test_neighbours_of_meetings_too_many_for_a_task(spark, monkeypatch):
    monkeypatch.setattr(compact, "MOST_MEMBERS", 0)
    own = members(5)
    assert rows(SlotGraph(spark.createDataFrame(own, "v bigint, t bigint")).static) == sorted({(u, v) for u, t in own for v, s in own if s == t and u != v})


def test_dense_solve_of_slots_lists_no_edges(spark, monkeypatch):
    slots = spark.createDataFrame([(v, t) for v, t in {(v * v % 11, t) for t in range(9) for v in range(t, t + 4)}], "v bigint, t bigint")
    g, one, q = SlotGraph(slots), F.lit(1).cast("bigint").alias("graph"), spark.createDataFrame([(1, 4), (1, 9)], "graph bigint, q bigint")
    got = lambda table: {(r["q"], r["v"]): r["prox"] for r in udf.proximity_by_graph(table, q, method="dense").collect()}
    want = got(g.edges.select(one, "u", "v", "t"))
    assert want.keys() == got(g.slots.select(one, "v", "t")).keys()
    monkeypatch.setattr(udf, "MOST_DENSE", 4)
    by_slots = got(g.slots.select(one, "v", "t"))
    assert want.keys() == by_slots.keys() and all(abs(want[k] - by_slots[k]) < 1e-12 for k in want)


def test_query_of_dense_solve_lists_no_edges(spark, monkeypatch):
    def listed(_):
        raise AssertionError("edges are listed")

    monkeypatch.setattr(SlotGraph, "edges", property(listed))
    assert surroundings.QUERIES["prox_dense_solve"](spark, SF).count() > 0

"""Sources, plans, functions, streams and the driver's entry."""

import datetime
import os

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from proxcore import catalog
from proxcore.functions import udf
from proxcore.plans import inspect
from proxcore.runtime import settle, sweep
from proxcore.sources import edge_lists, tables
from proxcore.sources.views import VIEWS
from proxcore.streaming import events as E
from tests.graphs import BASIC, graph

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("kind", ["text", "csv", "json", "parquet"])
def test_edge_lists_round_trip(spark, tmp_path, kind):
    path = str(tmp_path / kind)
    edge_lists.write_edges(graph(spark, BASIC), path, kind)
    assert sorted(map(tuple, edge_lists.read_edges(spark, path, kind).edges.collect())) == sorted(BASIC)


def test_text_edges_skip_what_isn_t_an_edge(spark, tmp_path):
    (tmp_path / "e.txt").write_text("# a comment\n1 2 3\n\nx y z\n 2\t1  3\n4 4 1\n5 6\n")
    assert list(map(tuple, edge_lists.read_edges(spark, str(tmp_path / "e.txt")).edges.collect())) == [(1, 2, 3)]


def test_store_prunes_slabs(spark, tmp_path):
    edge_lists.store(graph(spark, BASIC), str(tmp_path / "g"), 2)
    g = edge_lists.open_store(spark, str(tmp_path / "g"), 2, 3, 5)
    assert sorted(map(tuple, g.edges.collect())) == [e for e in sorted(BASIC) if 3 <= e[2] < 5]
    assert any("slab" in x for x in inspect.partition_filters(g.edges))


def test_plans_push_filters_and_prune_columns(spark):
    df = tables.table(spark, SF, "orders").where("o_totalprice > 1000").select("o_orderkey", "o_custkey")
    assert any("o_totalprice" in x for x in inspect.pushed_filters(df)) and not any("o_orderpriority" in x for x in inspect.read_schemas(df))
    assert not inspect.problems(VIEWS["copurchase_q1"](spark, SF).edges)


def test_settled_tables_can_be_swept(spark):
    df = settle(spark.range(5).toDF("x"))
    assert df.count() == 5 and sweep(spark) >= 1


def test_functions(spark):
    udf.register(spark)
    edges = spark.createDataFrame([(1, *e) for e in BASIC] + [(2, *e) for e in BASIC], "graph bigint, u bigint, v bigint, t bigint")
    got = udf.communities_by_graph(edges, spark.createDataFrame([(1, 2), (2, 1)], "graph bigint, q bigint")).collect()
    assert {r["v"] for r in got if r["graph"] == 1} == {2, 3, 4, 5} and {r["v"] for r in got if r["graph"] == 2} == {1, 2, 3, 4, 5}
    graph(spark, BASIC).arcs.createOrReplaceTempView("arcs")
    rows = spark.sql("SELECT * FROM later_neighbours(since => 3, row => TABLE(SELECT * FROM arcs WHERE src = 3) PARTITION BY src ORDER BY t)").collect()
    assert sorted((r["v"], r["t"], r["wait"]) for r in rows) == [(4, 4, 1), (5, 5, 2)]
    assert spark.sql("SELECT hyperbolic_decay(1) AS x").first()["x"] == 0.5
    udf.macro(spark, "some_view", spark.range(3).toDF("x"))
    assert spark.sql("SELECT count(*) AS n FROM some_view").first()["n"] == 3


@pytest.fixture
def stream_folder(spark, tmp_path):
    d = str(tmp_path / "events")
    tables.table(spark, SF, "events").orderBy("ts").coalesce(1).write.parquet(d)
    return d


def test_streams_agree_with_batches(spark, stream_folder, tmp_path):
    batch = tables.table(spark, SF, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    live = E.source(spark, stream_folder)
    want = {(r["start"], r["event_type"]): r["n"] for r in E.hourly(batch).collect()}
    got = {(r["start"], r["event_type"]): r["n"] for r in E.drain(E.hourly(live), "hours", "complete").collect()}
    assert got == want
    users = {r["user_id"]: r["n"] for r in E.drain(E.last_seen(E.source(spark, stream_folder)), "seen", "update").collect()}
    slots = batch.select("user_id", F.floor(F.unix_timestamp("ts") / 3600).alias("s")).distinct().groupBy("user_id").count().collect()
    assert users == {r["user_id"]: r["count"] for r in slots}
    pairs = {tuple(r) for r in E.drain(E.meetings(E.source(spark, stream_folder)), "met").select("u", "v", "t").collect()}
    assert pairs == {tuple(r) for r in VIEWS["meet10"](spark, SF).edges.collect()}
    assert E.drain(E.bursts(E.source(spark, stream_folder)), "bursts", "complete").agg(F.sum("n")).first()[0] == batch.count()


def test_streams_reach_no_table_in_memory(spark, stream_folder):
    """What a stream returns is in files, so its size is no matter of the driver's memory."""
    for mode, make in (("append", E.once), ("complete", E.bursts)):
        got = E.drain(make(E.source(spark, stream_folder)), f"files_{mode}", mode)
        assert got.inputFiles() and not spark.catalog.tableExists(f"files_{mode}")
        assert got.agg(F.count("*") if mode == "append" else F.sum("n")).first()[0] == tables.table(spark, SF, "events").count()


def test_whole_tables_stream_as_one_batch(spark, tmp_path):
    """A later file repeats the times of an earlier one: the watermark keeps out none of its rows."""
    rows = tables.table(spark, SF, "events")
    for k in range(2):
        rows.withColumns({c: F.col(c) + k * 1_000_000 for c in ("event_id", "user_id")}).coalesce(1).write.mode("append").parquet(str(tmp_path / "events.parquet"))
    from proxcore.catalog import surroundings

    assert surroundings.QUERIES["stream_once"](spark, str(tmp_path)).count() == 2 * rows.count()


def test_interval_degree_works_out_no_proximity(spark, monkeypatch):
    from proxcore.catalog import community

    community._base.cache_clear()
    monkeypatch.setattr(community, "prox_hops", None)
    assert community.QUERIES["interval_degree"](spark, SF).count() <= 1


def test_late_rows_and_repeats_are_dropped(spark, tmp_path):
    row = lambda i, h: (i, datetime.datetime(2024, 1, 1, h), 1, "view", 1.0, "{}")
    folder = tmp_path / "in"
    for k, part in enumerate([[row(1, 1), row(2, 20)], [row(5, 21)], [row(5, 21), row(3, 2), row(4, 22)]]):
        df = spark.createDataFrame(part, tables.SCHEMAS["events"].replace("timestamp_ntz", "timestamp")).withColumn("ts", F.col("ts").cast("timestamp_ntz"))
        df.coalesce(1).write.mode("append").parquet(str(folder))
        os.utime(sorted(folder.glob("*.parquet"), key=lambda p: p.stat().st_mtime)[-1], (1000 + k, 1000 + k))
    ids = sorted(r["event_id"] for r in E.drain(E.once(E.source(spark, str(folder))), "once").collect())
    assert ids == [1, 2, 4, 5]  # row 5 comes twice; row 3 is behind the watermark, which takes effect a batch later


def test_continuous_query(spark, stream_folder, tmp_path):
    seen = []
    q = E.follow(E.source(spark, stream_folder), [0, 3], str(tmp_path / "store"), str(tmp_path / "ck"), lambda df, n: seen.append((n, df.count())))
    q.awaitTermination()
    assert seen and seen[-1][1] >= 0


def test_entry_and_names(spark):
    assert {"q", "v", "beta_e9"} == set(__spark_entry__.entry(spark).columns)
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


@pytest.mark.parametrize("name", ["edges_meet10", "decay_norms_log", "prox_copurchase_q1", "exact_copurchase", "core_numbers_trade_q1", "truss_numbers", "static_core", "temporal_conductance", "rel_asof_join", "rel_interval_join", "rel_runs", "rel_cube"])
def test_queries_match_their_sql(spark, name):
    db = duckdb.connect()
    for t in tables.SCHEMAS:
        db.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    got, want = catalog.queries()[name](spark, SF), db.sql(catalog.oracle_sql()[name])
    columns = sorted(got.columns)
    assert columns == sorted(want.columns)
    rows = lambda x: sorted(repr(tuple(r)) for r in x)
    assert rows(got.select(columns).collect()) == rows(want.select(", ".join(columns)).fetchall())


def _purchases(spark, folder, batches):
    for k, part in enumerate(batches):
        rows = [(100 * k + i, datetime.datetime(2024, 1, 1, h, m), u, "purchase", 1.0, "{}") for i, (h, m, u) in enumerate(part)]
        df = spark.createDataFrame(rows, tables.SCHEMAS["events"].replace("timestamp_ntz", "timestamp")).withColumn("ts", F.col("ts").cast("timestamp_ntz"))
        df.coalesce(1).write.mode("append").parquet(str(folder))
        os.utime(sorted(folder.glob("*.parquet"), key=lambda p: p.stat().st_mtime)[-1], (1000 + k, 1000 + k))
    return E.source(spark, str(folder))


def test_gatherings_over_batches(spark, tmp_path):
    """Users of one slot meet across batches, each pair once; a slot behind the watermark is closed."""
    live = _purchases(spark, tmp_path / "in", [[(1, 1, 3), (1, 2, 3), (1, 3, 1)], [(1, 4, 2), (1, 5, 1), (20, 0, 7)], [(21, 0, 8)], [(1, 6, 9), (20, 5, 8)]])
    got = sorted(tuple(r) for r in E.pairs(E.drain(E.gatherings(live), "gathered")).select("u", "v").collect())
    assert got == [(1, 2), (1, 3), (2, 3), (7, 8)]  # 9 is late


def test_meetings_keep_users_not_pairs(spark, monkeypatch):
    """the stream's state had every purchase twice, and its files had every pair."""
    from proxcore.catalog import surroundings

    kept = []
    monkeypatch.setattr(E, "drain", lambda *a, drain=E.drain: kept.append(drain(*a)) or kept[-1])
    got = [tuple(r) for r in surroundings.QUERIES["stream_meetings"](spark, SF).collect()]
    users = VIEWS["meet10"](spark, SF).slots
    assert kept[0].count() == users.select("t").distinct().count() and kept[0].selectExpr("sum(size(fresh))").first()[0] == users.count()
    assert sorted(got) == sorted(tuple(r) for r in VIEWS["meet10"](spark, SF).edges.collect())

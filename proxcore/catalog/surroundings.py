"""Sources, sinks, streams and functions, each on a whole table and against a batch in SQL."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from proxcore.catalog import sql as S
from proxcore.catalog.structure import e9, pick
from proxcore.functions import udf
from proxcore.runtime import shared_dir
from proxcore.sources import edge_lists
from proxcore.sources.data_source import EdgeLines
from proxcore.sources.tables import table
from proxcore.sources.views import EDGE_SQL, VIEWS
from proxcore.streaming import events as E

Q = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Q] = {}
SQL: dict[str, str] = {}


def put(name: str, make: Q, text: str) -> None:
    QUERIES[name], SQL[name] = make, text


def _fresh(s: SparkSession, what: str) -> str:
    return f"{shared_dir(s)}/{what}-{uuid.uuid4().hex}"


def _round_trip(kind: str) -> Q:
    def run(s: SparkSession, d: str) -> DataFrame:
        path = _fresh(s, f"edges-{kind}")
        edge_lists.write_edges(VIEWS["trade"](s, d), path, "text" if kind == "python" else kind)
        if kind == "python":
            s.dataSource.register(EdgeLines)
            return s.read.format(EdgeLines.name()).load(path)
        return edge_lists.read_edges(s, path, kind).edges

    return run


for _kind in ("text", "csv", "json", "parquet", "orc", "python"):
    put(f"edge_list_{_kind}", _round_trip(_kind), EDGE_SQL["trade"])


def _slabs(s: SparkSession, d: str) -> DataFrame:
    path = _fresh(s, "slabs")
    edge_lists.store(VIEWS["trade_q1"](s, d), path, 7)
    return edge_lists.open_store(s, path, 7, 20, 60).edges


def _bucketed(s: SparkSession, d: str) -> DataFrame:
    g, name = VIEWS["trade"](s, d).settled(), f"arcs_{uuid.uuid4().hex}"
    edge_lists.store_arcs(g, name, 8, _fresh(s, "arcs"))
    return edge_lists.arcs_of(s, name, pick(g, 50))


put("store_slabs", _slabs, f"SELECT * FROM ({EDGE_SQL['trade_q1']}) WHERE t >= 20 AND t < 60")
put("store_buckets", _bucketed, S.query(S.graph("trade"), S.picked(50), select="SELECT src, dst, t FROM arcs JOIN qs ON src = q"))


def _live(s: SparkSession, d: str) -> DataFrame:
    """The whole table as one batch: its files are in no order of time, and a watermark would keep out what a later file repeats."""
    return E.source(s, f"{d}/events.parquet*", 1_000_000)


def _name() -> str:
    return f"s_{uuid.uuid4().hex}"


def _spread(df: DataFrame) -> DataFrame:
    """In more parts than tasks run at once, for few rows that become many."""
    return df.repartition(4 * df.sparkSession.sparkContext.defaultParallelism)


def _hour() -> F.Column:
    return F.floor(F.unix_timestamp("start") / 3600).alias("hour")


_BY_HOUR = "SELECT CAST(floor(epoch(ts) / 3600) AS BIGINT) AS hour, event_type, count(*) AS n FROM events GROUP BY hour, event_type"
put("stream_hours_complete", lambda s, d: E.drain(E.hourly(_live(s, d)), _name(), "complete").select(_hour(), "event_type", "n"), _BY_HOUR)
put("stream_hours_append", lambda s, d: E.drain(E.hourly(_live(s, d)), _name()).select(_hour(), "event_type", "n"), f"SELECT * FROM ({_BY_HOUR}) WHERE (hour + 1) * 3600 <= (SELECT floor(max(epoch(ts))) - 7200 FROM events)")
put("stream_hours_update", lambda s, d: E.drain(E.hourly(_live(s, d)), _name(), "update").groupBy(_hour(), "event_type").agg(F.max("n").alias("n")), _BY_HOUR)
put("stream_sliding", lambda s, d: E.drain(E.hourly(_live(s, d), slide="30 minutes"), _name(), "complete").select(F.floor(F.unix_timestamp("start") / 1800).alias("half_hour"), "event_type", "n"), "SELECT CAST(floor(epoch(ts) / 1800) AS BIGINT) - k AS half_hour, event_type, count(*) AS n FROM events, (VALUES (0), (1)) x(k) GROUP BY half_hour, event_type")
put("stream_sessions", lambda s, d: E.drain(E.bursts(_live(s, d)), _name(), "complete").select("user_id", F.unix_micros("start").alias("start_us"), "n"), """
WITH m AS (SELECT user_id, epoch_us(ts) AS tick, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER w < 1800000000 THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
r AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY tick) AS run FROM m)
SELECT user_id, min(tick) AS start_us, count(*) AS n FROM r GROUP BY user_id, run""")
put("stream_meetings", lambda s, d: E.pairs(_spread(E.drain(E.gatherings(_live(s, d)), _name()))), EDGE_SQL["meet10"])
put("stream_last_seen", lambda s, d: E.drain(E.last_seen(_live(s, d)), _name(), "update"), "SELECT user_id, count(DISTINCT floor(epoch(ts) / 3600)) AS n, CAST(max(floor(epoch(ts) / 3600)) AS BIGINT) AS last FROM events GROUP BY user_id")
put("stream_once", lambda s, d: E.drain(E.once(_live(s, d)), _name()).select("event_id"), "SELECT event_id FROM events")


def _late(s: SparkSession, d: str) -> DataFrame:
    """The later half of the events is followed by the earlier half, which the watermark then keeps out."""
    folder, out, checkpoint = _fresh(s, "late-in"), _fresh(s, "late-out"), _fresh(s, "late-checkpoint")
    rows = table(s, d, "events")
    for half in ("ts >= timestamp_ntz'2024-01-15 00:00:00'", "ts < timestamp_ntz'2024-01-15 00:00:00'"):
        rows.where(half).write.mode("append").parquet(folder)
        E.land(E.once(E.source(s, folder, 1000)), out, checkpoint)
    return s.read.parquet(out).select("event_id")


put("stream_late_rows", _late, "SELECT event_id FROM events WHERE ts >= TIMESTAMP '2024-01-15 00:00:00'")


def _follow(s: SparkSession, d: str) -> DataFrame:
    out = _fresh(s, "answers")
    wanted = [r["q"] for r in pick(VIEWS["meet10"](s, d), 4).collect()]
    E.follow(_live(s, d), wanted, _fresh(s, "slots"), _fresh(s, "checkpoint"), lambda df, n: df.write.mode("overwrite").parquet(f"{out}/batch={n}")).awaitTermination()
    answers = s.read.option("basePath", out).parquet(f"{out}/batch=*")
    return answers.join(answers.agg(F.max("batch").alias("batch")), "batch", "left_semi").select("q", "v", e9("beta"))


put("stream_follow", _follow, S.query(S.graph("meet10"), S.picked(4), S.prox(), S.peel(), S.exact(), select="SELECT comp.q, comp.v, beta AS beta_e9 FROM comp JOIN own ON own.q = comp.q"))


def _sequential(view: str, k: int, method: str) -> Q:
    def run(s: SparkSession, d: str) -> DataFrame:
        g = VIEWS[view](s, d).settled()
        one = F.lit(1).cast("bigint").alias("graph")
        rows = g.edges.select(one, "u", "v", "t") if g.slots is None else g.slots.select(one, "v", "t")
        out = udf.proximity_by_graph(rows, pick(g, k).select(one, "q"), method=method)
        return out.where("round(prox * 1e9) > 0").select("q", "v", e9("prox"))

    return run


_PROX = "SELECT q, v, CAST(round(prox * 1e9) AS BIGINT) AS prox_e9 FROM prox WHERE round(prox * 1e9) > 0"
put("prox_stream_pass", _sequential("copurchase_q1", 8, "stream"), S.query(S.graph("copurchase_q1"), S.picked(8), S.prox(), select=_PROX))
put("prox_dense_solve", _sequential("meet10", 4, "dense"), S.query(S.graph("meet10"), S.picked(4), S.prox(), select=_PROX))


def _later(s: SparkSession, d: str) -> DataFrame:
    udf.register(s)
    VIEWS["trade_q1"](s, d).arcs.createOrReplaceTempView("arcs_of_trade")
    return s.sql("SELECT v, t, wait FROM later_neighbours(since => 30, row => TABLE(SELECT * FROM arcs_of_trade) PARTITION BY src ORDER BY t)")


def _functions(s: SparkSession, d: str) -> DataFrame:
    udf.register(s)
    table(s, d, "events").createOrReplaceTempView("events_of_users")
    return s.sql("SELECT user_id, round(smallest_value(hyperbolic_decay(value)) * 1e9) :: bigint AS least_e9 FROM events_of_users GROUP BY user_id")


put("later_neighbours", _later, f"WITH {S.graph('trade_q1')} SELECT dst AS v, t, t - 30 AS wait FROM arcs WHERE t > 30")
put("vector_functions", _functions, "SELECT user_id, CAST(round(min(1 / (1 + value)) * 1e9) AS BIGINT) AS least_e9 FROM events GROUP BY user_id")

"""Graphs, transitions and proximity."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from proxcore import proximity as P
from proxcore import transitions
from proxcore.catalog import sql as S
from proxcore.graph import TemporalGraph, portable_hash
from proxcore.local import push_temporal
from proxcore.runtime import settle
from proxcore.sources.tables import table
from proxcore.sources.views import EDGE_SQL, VIEWS

Q = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Q] = {}
SQL: dict[str, str] = {}


def pick(g: TemporalGraph, k: int) -> DataFrame:
    """q: the k vertices of the least hash."""
    return g.vertices.orderBy(portable_hash(F.col("v")), "v").limit(k).select(F.col("v").alias("q"))


def e9(name: str, out: str | None = None) -> F.Column:
    return F.round(F.col(name) * 1e9).cast("bigint").alias(out or f"{name}_e9")


def put(name: str, make: Q, text: str | None = None) -> None:
    QUERIES[name] = make
    if text:
        SQL[name] = text


for _v in VIEWS:
    put(f"edges_{_v}", lambda s, d, v=_v: VIEWS[v](s, d).edges, EDGE_SQL[_v])
    put(f"static_{_v}", lambda s, d, v=_v: VIEWS[v](s, d).static, f"WITH e AS ({EDGE_SQL[_v]}) SELECT u AS v, v AS nbr FROM e UNION SELECT v, u FROM e")
put("vertex_stats", lambda s, d: VIEWS["trade"](s, d).vertex_stats(), f"WITH {S.graph('trade')} SELECT src AS v, count(DISTINCT t) AS t_count, count(*) AS temporal_degree, count(DISTINCT dst) AS degree FROM arcs GROUP BY src")
put("graph_describe", lambda s, d: VIEWS["trade"](s, d).describe(), f"WITH {S.graph('trade')} SELECT (SELECT count(DISTINCT src) FROM arcs) AS n, (SELECT count(*) FROM e) AS m, (SELECT count(*) FROM st) // 2 AS m_static, (SELECT max(c) FROM (SELECT count(DISTINCT t) AS c FROM arcs GROUP BY src)) AS t_max, (SELECT count(DISTINCT t) FROM e) AS n_times")
put("slice_edges", lambda s, d: VIEWS["trade_q1"](s, d).slice(10, 40).edges, f"SELECT * FROM ({EDGE_SQL['trade_q1']}) WHERE t >= 10 AND t < 40")
put("coarsen_edges", lambda s, d: VIEWS["trade_q1"](s, d).coarsen(7).edges, f"SELECT DISTINCT u, v, CAST(floor(t / 7) AS BIGINT) AS t FROM ({EDGE_SQL['trade_q1']})")
_SMALL = "SELECT p_partkey FROM part WHERE p_size <= 25"
put("induced_edges", lambda s, d: VIEWS["copurchase"](s, d).induced(_small(s, d)).edges, f"SELECT u, v, t FROM ({EDGE_SQL['copurchase']}) WHERE u IN ({_SMALL}) AND v IN ({_SMALL})")
put("neighbours_in_set", lambda s, d: VIEWS["copurchase"](s, d).neighbours(_small(s, d)).select("v", F.array_join(F.transform("neighbours", lambda x: x.cast("string")), ",").alias("neighbours")), f"WITH {S.graph('copurchase')} SELECT v, string_agg(CAST(nbr AS VARCHAR), ',' ORDER BY nbr) AS neighbours FROM st WHERE v IN ({_SMALL}) AND nbr IN ({_SMALL}) GROUP BY v")
put("out_arcs", lambda s, d: (g := VIEWS["trade"](s, d).settled()).out_arcs(pick(g, 1).first()["q"]), S.query(S.graph("trade"), S.picked(1), select="SELECT src, dst, t FROM arcs JOIN qs ON src = q"))
put("in_arcs", lambda s, d: (g := VIEWS["trade"](s, d).settled()).in_arcs(pick(g, 1).first()["q"]), S.query(S.graph("trade"), S.picked(1), select="SELECT src, dst, t FROM arcs JOIN qs ON dst = q"))
put("stream_order", lambda s, d: _stream_order(s, d), f"SELECT u, v, t, row_number() OVER (ORDER BY t, u, v) - 1 AS place FROM ({EDGE_SQL['trade']})")
put("seeds_query", lambda s, d: _seeds(s, d, "query"), S.query(S.graph("trade_q1"), S.picked(4), select="SELECT q, src, dst, t, CAST(round(1e9 / count(*) OVER (PARTITION BY q)) AS BIGINT) AS mass_e9 FROM qs JOIN arcs ON src = q"))
put("seeds_union", lambda s, d: _seeds(s, d, "union"), S.query(S.graph("trade_q1"), S.picked(4), select="SELECT (SELECT min(q) FROM qs) AS q, src, dst, t, CAST(round(1e9 / count(*) OVER ()) AS BIGINT) AS mass_e9 FROM qs JOIN arcs ON src = q"))
for _k in (20, 40, 60, 80):
    put(f"sample_edges_{_k}", lambda s, d, k=_k: VIEWS["trade"](s, d).sample(k, "edge").edges, f"SELECT * FROM ({EDGE_SQL['trade']}) WHERE (((((u * 31 + v) * 31 + t) % 2147483648) * 2654435761) % 4294967296) % 100 < {_k}")
    put(f"sample_vertices_{_k}", lambda s, d, k=_k: VIEWS["trade"](s, d).sample(k).edges, f"SELECT * FROM ({EDGE_SQL['trade']}) WHERE (((u % 2147483648) * 2654435761) % 4294967296) % 100 < {_k} AND (((v % 2147483648) * 2654435761) % 4294967296) % 100 < {_k}")
for _d, _spec in (("reciprocal", "reciprocal"), ("exp", ("exp", 0.1)), ("log", "log")):
    put(f"decay_norms_{_d}", lambda s, d, x=_spec: transitions.norms(VIEWS["trade_q1"](s, d), x).select("v", "t", "n_out", F.coalesce(F.round(F.col("norm") * 1e9).cast("bigint"), F.lit(-1)).alias("norm_e9"), "dangling"), f"WITH {S.graph('trade_q1', _d)} SELECT v, t, n_out, coalesce(CAST(round(norm * 1e9) AS BIGINT), -1) AS norm_e9, norm IS NULL AS dangling FROM nm")
put("decay_norms_exp_window", lambda s, d: transitions.norms_exponential(VIEWS["trade_q1"](s, d), 0.1).select("v", "t", "n_out", F.coalesce(F.round(F.col("norm") * 1e6).cast("bigint"), F.lit(-1)).alias("norm_e6"), "dangling"), f"WITH {S.graph('trade_q1', 'exp')} SELECT v, t, n_out, coalesce(CAST(round(norm * 1e6) AS BIGINT), -1) AS norm_e6, norm IS NULL AS dangling FROM nm")
put("dangling_states", lambda s, d: transitions.norms(VIEWS["trade"](s, d)).where("dangling").select("v", "t"), f"WITH {S.graph('trade')} SELECT v, max(t) AS t FROM occ GROUP BY v")
put("transition_rowsum", lambda s, d: transitions.check_stochastic(VIEWS["trade_q1"](s, d)).select("src", "dst", "t", e9("total")), f"WITH {S.graph('trade_q1')} SELECT src, dst, t, CAST(1000000000 AS BIGINT) AS total_e9 FROM arcs")
_REACH = "reach(v, t) AS (SELECT dst, t FROM arcs WHERE src = (SELECT min(q) FROM qs) UNION SELECT a.dst, a.t FROM reach r JOIN arcs a ON a.src = r.v AND a.t > r.t)"
put("reachable_states", lambda s, d: _reach(s, d), S.query(S.graph("trade_q1"), S.picked(1), _REACH, select="SELECT DISTINCT v, t FROM reach"))


def _small(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "part").where("p_size <= 25").select("p_partkey")


def _stream_order(s: SparkSession, d: str) -> DataFrame:
    """Places in the stream: numbers within range partitions, and where each partition starts."""
    rows = VIEWS["trade"](s, d).settled().stream_order().withColumns({"part": F.spark_partition_id(), "k": F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))})
    rows = settle(rows)
    sizes = rows.groupBy("part").agg(F.count("*").alias("n"))
    starts = sizes.alias("a").join(sizes.alias("b"), F.col("b.part") < F.col("a.part"), "left").groupBy("a.part").agg(F.coalesce(F.sum("b.n"), F.lit(0)).alias("start"))
    return rows.join(F.broadcast(starts), "part").select("u", "v", "t", (F.col("start") + F.col("k")).alias("place"))  # a row for each partition


def _seeds(s: SparkSession, d: str, start: str) -> DataFrame:
    g = VIEWS["trade_q1"](s, d).settled()
    return P.seeds(g, pick(g, 4), start).select("q", "src", "dst", "t", e9("mass"))


def _reach(s: SparkSession, d: str) -> DataFrame:
    g = VIEWS["trade_q1"](s, d).settled()
    return transitions.reachable_states(g, pick(g, 1).first()["q"])


def _prox(view: str, k: int, make=P.prox, **how: object) -> Q:  # noqa: ANN001
    def run(s: SparkSession, d: str) -> DataFrame:
        g = VIEWS[view](s, d).settled()
        return make(g, pick(g, k), **how).where("round(prox * 1e9) > 0").select("q", "v", e9("prox"))

    return run


_OUT = "SELECT q, v, CAST(round(prox * 1e9) AS BIGINT) AS prox_e9 FROM prox WHERE round(prox * 1e9) > 0"
for _v, _k in (("copurchase_q1", 8), ("trade_q1", 5), ("meet10", 5)):
    put(f"prox_{_v}", _prox(_v, _k), S.query(S.graph(_v), S.picked(_k), S.prox(), select=_OUT))
put("prox_alpha_08", _prox("copurchase_q1", 8, alpha=0.8), S.query(S.graph("copurchase_q1"), S.picked(8), S.prox(0.8), select=_OUT))
put("prox_decay_log", _prox("copurchase_q1", 8, decay="log"), S.query(S.graph("copurchase_q1", "log"), S.picked(8), S.prox(0.2, "log"), select=_OUT))
put("prox_decay_exp", _prox("copurchase_q1", 8, decay=("exp", 0.1)), S.query(S.graph("copurchase_q1", "exp"), S.picked(8), S.prox(0.2, "exp"), select=_OUT))
put("prox_power", _prox("copurchase_q1", 2, P.prox_power, tol=1e-11), S.query(S.graph("copurchase_q1"), S.picked(2), S.prox(), select=_OUT))
put("prox_slabs", _prox("copurchase_q1", 3, P.prox_slabs, slab=15), S.query(S.graph("copurchase_q1"), S.picked(3), S.prox(), select=_OUT))
_ONE = S.query(S.graph("trade_q1"), S.picked(5), S.prox(), select="SELECT q, CAST(round(sum(prox) * 1e9) AS BIGINT) AS mass_e9 FROM prox GROUP BY q")
put("prox_mass", lambda s, d: _mass(s, d), _ONE)
_TOP = "SELECT q, v, CAST(row_number() OVER (PARTITION BY q ORDER BY round(prox * 1e9) DESC, v) AS INTEGER) AS place FROM prox QUALIFY place <= 5"
put("prox_topk", lambda s, d: _top(s, d), S.query(S.graph("trade_q1"), S.picked(5), S.prox(), select=_TOP))
for _c, _x in (("mean", "sum(prox) / 3"), ("min", "CASE WHEN count(*) = 3 THEN min(prox) ELSE 0 END"), ("product", "CASE WHEN count(*) = 3 THEN product(prox) ELSE 0 END")):
    put(f"prox_multi_{_c}", lambda s, d, c=_c: _multi(s, d, c), S.query(S.graph("trade_q1"), S.picked(3), S.prox(), select=f"SELECT v, CAST(round(({_x}) * 1e9) AS BIGINT) AS prox_e9 FROM prox GROUP BY v"))
_WALKS = """mat AS MATERIALIZED (SELECT a.src, a.dst, a.t, b.src AS src2, b.dst AS dst2, b.t AS t2, (1.0 / (b.t - a.t)) / nm.norm AS p FROM arcs a JOIN nm ON nm.v = a.dst AND nm.t = a.t JOIN arcs b ON b.src = a.dst AND b.t > a.t
  UNION ALL SELECT a.src, a.dst, a.t, a.src, a.dst, a.t, 1.0 FROM arcs a JOIN nm ON nm.v = a.dst AND nm.t = a.t WHERE norm IS NULL),
series(i, q, src, dst, t, mass) AS (SELECT 0, q, src, dst, t, 1.0 / count(*) OVER (PARTITION BY q) FROM qs JOIN arcs ON src = q
  UNION ALL SELECT i + 1, q, src2, dst2, t2, mass * p FROM series JOIN mat USING (src, dst, t) WHERE i < 2)"""
put("walk_series_depth3", _prox("copurchase_q1", 4, P.prox_walks, depth=3), S.query(S.graph("copurchase_q1"), S.picked(4), _WALKS, select="SELECT * FROM (SELECT q, dst AS v, CAST(round(sum(0.2 * pow(0.8, i) * mass) * 1e9) AS BIGINT) AS prox_e9 FROM series GROUP BY q, dst) WHERE prox_e9 > 0"))
_STATIC = """deg AS MATERIALIZED (SELECT v, count(*) AS d FROM st GROUP BY v),
step(i, q, v, mass) AS (SELECT 0, q, q, CAST(1 AS DOUBLE) FROM qs UNION ALL SELECT i + 1, q, st.nbr, sum(0.8 * mass / d) FROM step JOIN deg ON deg.v = step.v JOIN st ON st.v = step.v WHERE i < 7 GROUP BY i, q, st.nbr)"""
put("ppr_static", _prox("trade_q1", 3, P.ppr_static, rounds=8), S.query(S.graph("trade_q1"), S.picked(3), _STATIC, select="SELECT * FROM (SELECT q, v, CAST(round(sum(0.2 * mass) * 1e9) AS BIGINT) AS prox_e9 FROM step GROUP BY q, v) WHERE prox_e9 > 0"))
put("prox_sampled", lambda s, d: _sampled(s, d), S.query(S.graph("copurchase_q1"), S.picked(4), select="SELECT q, true AS close, CAST(1000000000 AS BIGINT) AS mass_e9 FROM qs"))
put("push_temporal", lambda s, d: _push_temporal(s, d), S.query(S.graph("copurchase_q1"), S.picked(4), select="SELECT q, CAST(1000000000 AS BIGINT) AS mass_e9, true AS small, true AS below FROM qs"))
_WORK = """met AS MATERIALIZED (SELECT walk.i, walk.q, walk.v, walk.t, mass, norm IS NOT NULL AS live FROM walk JOIN nm ON nm.v = walk.v AND nm.t = walk.t),
heads AS (SELECT i, q, v, min(t) AS first FROM met WHERE live GROUP BY i, q, v),
sent AS (SELECT i, q, sum(n_out) AS messages FROM heads JOIN occ ON occ.v = heads.v AND occ.t > first GROUP BY i, q)"""
put("work_counters", lambda s, d: _work(s, d), S.query(S.graph("trade_q1"), S.picked(4), S.prox(), _WORK, select="SELECT m.q, CAST(m.i AS BIGINT) AS round, count(*) AS states, count(*) FILTER (live) AS live, CAST(coalesce(any_value(messages), 0) AS BIGINT) AS messages, CAST(round(sum(mass) * 1e9) AS BIGINT) AS mass_e9 FROM met m LEFT JOIN sent ON sent.i = m.i AND sent.q = m.q GROUP BY m.q, m.i"))
put("push_static_mass", lambda s, d: _push(s, d), S.query(S.graph("trade_q1"), S.picked(3), select="SELECT q, CAST(1000000000 AS BIGINT) AS mass_e9, true AS small FROM qs"))


def _mass(s: SparkSession, d: str) -> DataFrame:
    g = VIEWS["trade_q1"](s, d).settled()
    return P.check_mass(P.prox_hops(g, pick(g, 5))).select("q", e9("mass"))


def _top(s: SparkSession, d: str) -> DataFrame:
    from pyspark.sql import Window

    g = VIEWS["trade_q1"](s, d).settled()
    place = F.row_number().over(Window.partitionBy("q").orderBy(F.desc(F.round(F.col("prox") * 1e9)), "v"))
    return P.prox_hops(g, pick(g, 5)).select("q", "v", place.alias("place")).where("place <= 5")


def _multi(s: SparkSession, d: str, combine: str) -> DataFrame:
    g = VIEWS["trade_q1"](s, d).settled()
    return P.prox_multi(P.prox_hops(g, pick(g, 3)), combine).select("v", e9("prox"))


def _sampled(s: SparkSession, d: str) -> DataFrame:
    """Shares of 4,000 walks lie within six standard errors (at most 0.048) of the scores."""
    g = VIEWS["copurchase_q1"](s, d).settled()
    q = settle(pick(g, 4))
    both = P.prox_sampled(g, q, walks=4000).join(P.prox_hops(g, q).withColumnRenamed("prox", "true"), ["q", "v"], "full").na.fill(0.0, ["prox", "true"])
    error = F.sqrt(F.col("true") * (1 - F.col("true")) / 4000)
    return both.groupBy("q").agg(F.every(F.abs(F.col("prox") - F.col("true")) <= 6 * error + 0.002).alias("close"), F.round(F.sum("prox") * 1e9).cast("bigint").alias("mass_e9"))


def _push_temporal(s: SparkSession, d: str) -> DataFrame:
    """Banked mass and residues sum to one, no arc holds the threshold, and no bound is above its score."""
    g = VIEWS["copurchase_q1"](s, d).settled()
    q = settle(pick(g, 4))
    lower, residue = push_temporal(g, q, least=1e-4)
    rest = residue.groupBy("q").agg(F.sum("r").alias("left"), F.max("r").alias("top"))
    low = lower.join(P.prox_hops(g, q), ["q", "v"], "left").groupBy("q").agg(F.sum("low").alias("banked"), F.every(F.col("low") <= F.coalesce("prox", F.lit(0.0)) + 1e-9).alias("below"))
    out = q.join(low, "q", "left").join(rest, "q", "left").na.fill(0.0, ["banked", "left", "top"])
    return out.select("q", F.round((F.col("banked") + F.col("left")) * 1e9).cast("bigint").alias("mass_e9"), (F.col("top") < 1e-4).alias("small"), "below")


def _work(s: SparkSession, d: str) -> DataFrame:
    g = VIEWS["trade_q1"](s, d).settled()
    return P.work_counters(g, pick(g, 4)).select("q", "round", "states", "live", "messages", e9("mass"))


def _push(s: SparkSession, d: str) -> DataFrame:
    """Reserve and residue sum to one, and no residue reaches the threshold."""
    g = VIEWS["trade_q1"](s, d).settled()
    degree = g.static.groupBy("v").agg(F.count("*").alias("deg"))
    out = P.push_static(g, pick(g, 3), least=1e-3).join(degree, "v", "left")
    return out.groupBy("q").agg(F.round(F.sum(F.col("reserve") + F.col("residue")) * 1e9).cast("bigint").alias("mass_e9"), F.every(F.col("residue") < 1e-3 * F.coalesce("deg", F.lit(1))).alias("small"))

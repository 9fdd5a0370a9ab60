"""Communities, baselines, measures and workloads."""

from __future__ import annotations

import functools
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from proxcore import compact, cores, exact, local, metrics, workloads
from proxcore import drift as D
from proxcore.baselines import heuristics, static, temporal
from proxcore.catalog import sql as S
from proxcore.catalog.structure import e9, pick
from proxcore.graph import TemporalGraph
from proxcore.proximity import prepared, prox_hops, prox_multi
from proxcore.runtime import forget_at_sweep, settle
from proxcore.sources.tables import table
from proxcore.sources.views import VIEWS

Q = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Q] = {}
SQL: dict[str, str] = {}


def put(name: str, make: Q, text: str | None = None) -> None:
    QUERIES[name] = make
    if text:
        SQL[name] = text


@functools.lru_cache(maxsize=32)
def _base(s: SparkSession, d: str, view: str, k: int) -> tuple[TemporalGraph, DataFrame | None, DataFrame, DataFrame, DataFrame]:
    """The settled graph, its static form, queries, proximity and units; shared by the queries over one view. A graph whose slots fit a
    task has no static form, for it grows with the square of a slot; what takes it from here then goes by slots."""
    g, states = prepared(VIEWS[view](s, d))
    q = settle(pick(g, k))
    by_slots = compact.ship_slots(g) is not None
    scores = settle(compact.proximity(g, q) if by_slots else prox_hops(g, q, states=states))
    return g, None if by_slots else settle(g.static), q, scores, settle(cores.in_units(scores))


def core_numbers(g: TemporalGraph, st: DataFrame | None, w: DataFrame) -> DataFrame:
    return compact.core_numbers(g, w) if st is None else cores.core_numbers(st, w)


def from_weights(g: TemporalGraph, st: DataFrame | None, w: DataFrame, q: DataFrame, method: str = "refine") -> DataFrame:
    return compact.from_weights(g, w, q) if st is None else exact.from_weights(st, w, q, method=method)


def smallest_degree(g: TemporalGraph, st: DataFrame | None, w: DataFrame, members: DataFrame) -> DataFrame:
    return compact.smallest_degree(g, w, members) if st is None else metrics.min_biased_degree(st, w, members)


forget_at_sweep(_base.cache_clear)


def on(view: str, k: int, f: Callable[..., DataFrame]) -> Q:
    return lambda s, d: f(*_base(s, d, view, k))


def graph_alone(view: str, f: Callable[[TemporalGraph], DataFrame]) -> Q:
    """Of the graph, for what needs no queries and no proximity."""
    return lambda s, d: f(VIEWS[view](s, d))


def _sql(view: str, k: int, *more: str, select: str) -> str:
    return S.query(S.graph(view), S.picked(k), S.prox(), *more, select=select)


_RHO = "SELECT q, st.nbr AS v, CAST(sum(units) AS BIGINT) AS rho FROM w JOIN st ON st.v = w.v GROUP BY q, st.nbr"
put("biased_degree", on("trade_q1", 5, lambda g, st, q, p, w: cores.biased_degree(st, w)), _sql("trade_q1", 5, select=_RHO))
for _v, _k in (("copurchase_q1", 8), ("trade_q1", 5), ("meet10", 4)):
    put(f"core_numbers_{_v}", on(_v, _k, lambda g, st, q, p, w: core_numbers(g, st, w)), _sql(_v, _k, S.peel(), select="SELECT q, v, core FROM core"))
put("threshold_core", on("trade_q1", 5, lambda g, st, q, p, w: cores.threshold_core(st, w, q.select("q", F.lit(20_000_000).alias("beta")))), _sql("trade_q1", 5, S.peel(), select="SELECT q, v FROM core WHERE core >= 20000000"))
put("component", on("copurchase_q1", 8, lambda g, st, q, p, w: cores.component(st, p.select("q", "v").unionByName(q.select("q", F.col("q").alias("v"))).distinct())), _sql("copurchase_q1", 8, S.component("SELECT q, v FROM prox UNION SELECT q, q FROM qs"), select="SELECT q, v FROM comp"))
put("connected_components", lambda s, d: cores.connected_components(VIEWS["copurchase_q1"](s, d).settled().static), S.query(S.graph("copurchase_q1"), "reach(v, label) AS (SELECT DISTINCT v, v FROM st UNION SELECT st.nbr, label FROM reach JOIN st ON st.v = reach.v)", select="SELECT v, min(label) AS label FROM reach GROUP BY v"))
_EXACT = "SELECT comp.q, comp.v, beta AS beta_e9 FROM comp JOIN own ON own.q = comp.q"


def _exact(method: str) -> Callable[..., DataFrame]:
    return lambda g, st, q, p, w: from_weights(g, st, w, q, method).select("q", "v", F.col("beta").cast("bigint").alias("beta_e9"))


for _v, _k in (("copurchase_q1", 8), ("trade_q1", 5), ("meet10", 4)):
    put(f"exact_{_v}".replace("_q1", "") if _v == "copurchase_q1" else f"exact_{_v}", on(_v, _k, _exact("refine")), _sql(_v, _k, S.peel(), S.exact(), select=_EXACT))
for _m, _k in (("peel", 4), ("bisect", 2)):
    put(f"exact_{_m}", on("copurchase_q1", _k, _exact(_m)), _sql("copurchase_q1", _k, S.peel(), S.exact(), select=_EXACT))
put("is_proximity_core", on("copurchase_q1", 8, lambda g, st, q, p, w: cores.is_proximity_core(st, w, (c := settle(exact.from_weights(st, w, q))), c.select("q", "beta").distinct())), _sql("copurchase_q1", 8, select="SELECT q, true AS holds FROM qs"))


def _multi(s: SparkSession, d: str) -> DataFrame:
    g, _, q, _, _ = _base(s, d, "trade_q1", 5)
    two = [r["q"] for r in q.orderBy("q").limit(2).collect()]
    return exact.exact_community_multi(g, two).select("v", F.round(F.col("beta") * 1e9).cast("bigint").alias("beta_e9"))


_MULTI = """two AS (SELECT q FROM qs ORDER BY q LIMIT 2),
mw AS MATERIALIZED (SELECT (SELECT min(q) FROM two) AS q, v, CAST(round(sum(prox) / 2 * 1e9) AS BIGINT) AS units FROM prox WHERE q IN (SELECT q FROM two) GROUP BY v HAVING round(sum(prox) / 2 * 1e9) > 0)"""
_MULTI_BEST = """lim AS (SELECT CASE WHEN count(*) = 2 THEN min(core) ELSE 0 END AS top FROM mc WHERE v IN (SELECT q FROM two)),
lvl AS MATERIALIZED (SELECT DISTINCT core AS l FROM mc, lim WHERE core <= top),
reach(l, v) AS (SELECT l, (SELECT min(q) FROM two) FROM lvl UNION SELECT r.l, st.nbr FROM reach r JOIN st ON st.v = r.v JOIN mc ON mc.v = st.nbr AND mc.core >= r.l),
best AS (SELECT max(l) AS l FROM (SELECT l FROM reach WHERE v IN (SELECT q FROM two) GROUP BY l HAVING count(*) = 2))"""
put("exact_multi", _multi, _sql("trade_q1", 5, _MULTI, S.peel("mw", name="mc"), _MULTI_BEST, select="SELECT v, reach.l AS beta_e9 FROM reach JOIN best ON best.l = reach.l"))


def certified(method: str, **how: object) -> Callable[..., DataFrame]:
    """q, has, joined, holds: a community of the local method has its query, is connected, and its smallest biased degree is
    within the certified ratio of the exact one."""

    def run(g: TemporalGraph, st: DataFrame | None, q: DataFrame, p: DataFrame, w: DataFrame) -> DataFrame:
        found = settle(local.local_community(g, q, method=method, **how))
        size = found.groupBy("q").agg(F.count("*").alias("n"), F.max(F.col("v") == F.col("q")).alias("has"))
        joined = cores.component(g.slots if st is None else st, found.select("q", "v")).groupBy("q").agg(F.count("*").alias("k"))
        got = smallest_degree(g, st, w, found).select("q", (F.col("rho") / 1e9).alias("beta"))
        best = from_weights(g, st, w, q).select("q", (F.col("beta") / 1e9).alias("best")).distinct()
        # scores count in whole units, so bounds hold up to the units of a vertex's neighbours
        holds = got.join(best, "q").join(found.select("q", "eps").distinct(), "q").select("q", ((F.col("beta") <= F.col("best") + 1e-7) & (F.col("best") <= F.col("eps") * (F.col("beta") + 1e-7))).alias("holds"))
        return size.join(joined, "q").join(holds, "q").select("q", "has", (F.col("k") == F.col("n")).alias("joined"), "holds")

    return run


def certificate(g: TemporalGraph, st: DataFrame | None, q: DataFrame, p: DataFrame, w: DataFrame, **how: object) -> DataFrame:
    """q, bounds, covered, ratio: lower <= rho <= lower + residue for all expanded vertices; the exact community is expanded;
    the smallest biased degree found is within the certified ratio of the exact one. By levels; by slots in a task a query where there is no
    static form."""
    if st is None:
        return compact.certificate(g, p, w, q, **how)
    members, lower, facts = local.expand_levels(g, q, **how)
    members, lower = settle(members), settle(lower)
    true = p.join(members.select("q", "v"), ["q", "v"], "left_semi").join(st, "v").groupBy("q", F.col("nbr").alias("v")).agg(F.sum("prox").alias("rho"))
    bounds = local.rho_bounds(st, members, lower, facts).join(true, ["q", "v"], "left").withColumn("rho", F.coalesce("rho", F.lit(0.0))).groupBy("q").agg(F.every((F.col("low") <= F.col("rho") + 1e-9) & (F.col("rho") <= F.col("high") + 1e-9)).alias("bounds"))
    best = settle(exact.from_weights(st, w, q))
    covered = best.where("beta > 0").join(members.select("q", "v", F.lit(1).alias("in")), ["q", "v"], "left").groupBy("q").agg(F.every(F.col("in").isNotNull()).alias("covered"))
    eps, found = local.shrink_levels(st, members, lower, facts)
    got = metrics.min_biased_degree(st, w, settle(found)).select("q", (F.col("rho") / 1e9).alias("beta"))
    ok = got.join(best.select("q", (F.col("beta") / 1e9).alias("best")).distinct(), "q").join(eps, "q").select("q", ((F.col("beta") <= F.col("best") + 1e-7) & (F.col("best") <= F.col("eps") * (F.col("beta") + 1e-7))).alias("ratio"))
    return bounds.join(covered, "q", "left").join(ok, "q").select("q", "bounds", F.coalesce("covered", F.lit(True)).alias("covered"), "ratio")


_TRUE = "SELECT q, true AS bounds, true AS covered, true AS ratio FROM qs"
put("local_certificate", on("copurchase_q1", 8, certificate), _sql("copurchase_q1", 8, select=_TRUE))
put("local_certificate_dense", on("meet10", 2, certificate), _sql("meet10", 2, select=_TRUE))
put("local_certificate_unpruned", on("copurchase_q1", 4, functools.partial(certificate, prune=False, stop=False)), _sql("copurchase_q1", 4, select=_TRUE))
_HOLDS = "SELECT q, true AS has, true AS joined, true AS holds FROM qs"
put("local_copurchase", on("copurchase_q1", 8, certified("levels")), _sql("copurchase_q1", 8, select=_HOLDS))
put("local_queue", on("copurchase_q1", 8, certified("queue")), _sql("copurchase_q1", 8, select=_HOLDS))
put("local_anchor_query", on("copurchase_q1", 8, certified("levels", anchor="query")), _sql("copurchase_q1", 8, select=_HOLDS))
put("local_task", on("trade_q1", 5, certified("task")), _sql("trade_q1", 5, select=_HOLDS))
put("local_task_dense", on("meet", 5, certified("task")), _sql("meet", 5, select=_HOLDS))


def _local_multi(s: SparkSession, d: str) -> DataFrame:
    """One row: the community has both queries, and its smallest biased degree under the mixed walk is within the certified
    ratio of the exact value."""
    g, st, q, p, _ = _base(s, d, "trade_q1", 5)
    two = [r["q"] for r in q.orderBy("q").limit(2).collect()]
    found = settle(local.local_community_multi(g, two))
    mixed = prox_multi(p.where(F.col("q").isin(two))).select(F.lit(two[0]).alias("q"), "v", "prox")
    got = metrics.min_biased_degree(st, cores.in_units(mixed), found.select(F.lit(two[0]).alias("q"), "v")).select((F.col("rho") / 1e9).alias("beta"))
    best = exact.exact_community_multi(g, two).agg(F.max("beta").alias("best"))
    has = found.agg(F.count_if(F.col("v").isin(two)).alias("k"), F.max("eps").alias("eps"))
    return got.crossJoin(best).crossJoin(has).select((F.col("k") == 2).alias("has"), ((F.col("beta") <= F.col("best") + 1e-7) & (F.col("best") <= F.col("eps") * (F.col("beta") + 1e-7))).alias("holds"))  # single rows


put("local_multi", _local_multi, "SELECT true AS has, true AS holds")
_FLOOR = """lev(i, q, v, level, alive) AS (
  SELECT 0, q, v, CAST(0 AS DOUBLE), true FROM prox WHERE prox > 0
  UNION ALL
  SELECT i + 1, q, v, theta, k > theta FROM (SELECT *, greatest(level, min(k) OVER (PARTITION BY q)) AS theta FROM (
    SELECT a.i, a.q, a.v, a.level, CASE WHEN count(b.v) >= 3 THEN any_value(p.prox) ELSE 0 END AS k
    FROM lev a JOIN prox p ON p.q = a.q AND p.v = a.v LEFT JOIN (SELECT l.q, l.v, st.v AS of FROM lev l JOIN st ON st.nbr = l.v WHERE l.alive) b ON b.q = a.q AND b.of = a.v WHERE a.alive GROUP BY a.i, a.q, a.v, a.level)))"""
put("floor_levels", on("trade_q1", 5, lambda g, st, q, p, w: static.floor_levels(st, p, 3).select("q", "v", e9("level"))), _sql("trade_q1", 5, _FLOOR, select="SELECT q, v, CAST(round(level * 1e9) AS BIGINT) AS level_e9 FROM lev WHERE NOT alive AND level > 0"))
_ONES = "ones AS MATERIALIZED (SELECT DISTINCT CAST(0 AS BIGINT) AS q, v, CAST(1 AS BIGINT) AS units FROM st)"
_LEVELS = "lv AS MATERIALIZED (SELECT qs.q, c.core AS k FROM qs JOIN core c ON c.v = qs.q)"
_CORE_IN = "SELECT lv.q, core.v FROM lv JOIN core ON core.core >= lv.k"
put("static_core", on("trade_q1", 5, lambda g, st, q, p, w: static.static_core(g, q)), S.query(S.graph("trade_q1"), S.picked(5), _ONES, S.peel("ones"), _LEVELS, S.component(_CORE_IN), select="SELECT comp.q, comp.v, lv.k FROM comp JOIN lv ON lv.q = comp.q"))
put("temporal_degree_core", on("trade_q1", 5, lambda g, st, q, p, w: static.static_core(g, q, "temporal", method="refine")), S.query(S.graph("trade_q1"), S.picked(5), _ONES, S.peel("ones", "SELECT src AS v, dst AS nbr, count(*) AS x FROM arcs GROUP BY src, dst"), _LEVELS, S.component(_CORE_IN), select="SELECT comp.q, comp.v, lv.k FROM comp JOIN lv ON lv.q = comp.q"))
_TRI = "tri AS MATERIALIZED (SELECT x.v AS a, x.nbr AS b, y.nbr AS c FROM st x JOIN st y ON y.v = x.nbr JOIN st z ON z.v = x.v AND z.nbr = y.nbr WHERE x.v < x.nbr AND y.v < y.nbr)"
put("triangles", on("copurchase_q1", 8, lambda g, st, q, p, w: static.triangles(st)), S.query(S.graph("copurchase_q1"), _TRI, select="SELECT a, b, c FROM tri"))
_TRUSS = """side AS MATERIALIZED (SELECT a AS u, b AS v, a AS u1, c AS v1, b AS u2, c AS v2 FROM tri UNION ALL SELECT a, c, a, b, b, c FROM tri UNION ALL SELECT b, c, a, b, a, c FROM tri),
peel(i, u, v, theta, alive) AS (SELECT 0, v, nbr, CAST(0 AS BIGINT), true FROM st WHERE v < nbr UNION ALL
  SELECT i + 1, u, v, level, n > level FROM (SELECT *, greatest(theta, min(n) OVER ()) AS level FROM (
    SELECT p.i, p.u, p.v, p.theta, count(s.u) AS n FROM peel p LEFT JOIN (SELECT s.u, s.v FROM side s JOIN peel x ON x.u = s.u1 AND x.v = s.v1 AND x.alive JOIN peel y ON y.u = s.u2 AND y.v = s.v2 AND y.alive) s ON s.u = p.u AND s.v = p.v WHERE p.alive GROUP BY p.i, p.u, p.v, p.theta)))"""
put("truss_numbers", on("copurchase_q1", 8, lambda g, st, q, p, w: static.truss_numbers(st)), S.query(S.graph("copurchase_q1"), _TRI, _TRUSS, select="SELECT u, v, theta + 2 AS k FROM peel WHERE NOT alive"))
_FLOOR_OWN = "fl AS MATERIALIZED (SELECT q, v, level FROM lev WHERE NOT alive AND level > 0), fo AS (SELECT qs.q, level AS floor FROM qs LEFT JOIN fl ON fl.q = qs.q AND fl.v = qs.q)"
_FLOOR_IN = "SELECT fl.q, fl.v FROM fl JOIN fo ON fo.q = fl.q WHERE fl.level >= fo.floor UNION ALL SELECT fo.q, pc.v FROM fo, pc WHERE fo.floor IS NULL AND pc.core >= 3"
_FLOOR_SQL = _sql("trade_q1", 5, _FLOOR, _FLOOR_OWN, _ONES, S.peel("ones", name="pc"), S.component(_FLOOR_IN), select="SELECT comp.q, comp.v, CAST(round(coalesce(floor, 0) * 1e9) AS BIGINT) AS floor_e9 FROM comp JOIN fo ON fo.q = comp.q")
put("floor_kcore", on("trade_q1", 5, lambda g, st, q, p, w: static.floor_kcore(g, q, k=3, prox=p).select("q", "v", e9("floor"))), _FLOOR_SQL)
put("floor_kcore_task", on("trade_q1", 5, lambda g, st, q, p, w: static.floor_kcore(g, q, k=3, method="task").select("q", "v", e9("floor"))), _FLOOR_SQL)
_TRUSS_JOIN = """ek AS MATERIALIZED (SELECT u, v, theta + 2 AS k FROM peel WHERE NOT alive),
tl AS (SELECT q, max(k) AS level FROM qs JOIN ek ON ek.u = q OR ek.v = q GROUP BY q),
sk AS MATERIALIZED (SELECT x.* FROM (SELECT s.u, s.v, s.u1, s.v1, s.u2, s.v2, least(a.k, b.k, c.k) AS k FROM side s JOIN ek a ON a.u = s.u AND a.v = s.v JOIN ek b ON b.u = s.u1 AND b.v = s.v1 JOIN ek c ON c.u = s.u2 AND c.v = s.v2) x),
nx AS MATERIALIZED (SELECT u, v, u1 AS x, v1 AS y, k FROM sk UNION ALL SELECT u, v, u2, v2, k FROM sk),
tc(q, u, v) AS (SELECT tl.q, ek.u, ek.v FROM tl JOIN ek ON (ek.u = tl.q OR ek.v = tl.q) AND ek.k = tl.level
  UNION SELECT tc.q, nx.x, nx.y FROM tc JOIN tl ON tl.q = tc.q JOIN nx ON nx.u = tc.u AND nx.v = tc.v AND nx.k >= tl.level)"""
put("truss_community", on("copurchase_q1", 8, lambda g, st, q, p, w: static.truss_community(g, q)), S.query(S.graph("copurchase_q1"), S.picked(8), _TRI, _TRUSS, _TRUSS_JOIN, select="SELECT m.q, m.x AS v, level AS k FROM (SELECT q, u AS x FROM tc UNION SELECT q, v FROM tc) m JOIN tl ON tl.q = m.q"))
_SWEEP = """deg AS MATERIALIZED (SELECT v, count(*) AS d FROM st GROUP BY v),
push(i, q, v, reserve, residue) AS (SELECT 0, q, q, CAST(0 AS DOUBLE), CAST(1 AS DOUBLE) FROM qs UNION ALL
  SELECT i, q, v, sum(a), sum(b) FROM (
    SELECT p.i + 1 AS i, p.q, p.v, p.reserve + CASE WHEN p.residue >= 1e-4 * d THEN 0.2 * p.residue ELSE 0 END AS a, CASE WHEN p.residue >= 1e-4 * d THEN 0 ELSE p.residue END AS b
    FROM push p JOIN deg ON deg.v = p.v WHERE p.q IN (SELECT x.q FROM push x JOIN deg y ON y.v = x.v WHERE x.residue >= 1e-4 * y.d)
    UNION ALL SELECT p.i + 1, p.q, st.nbr, 0, 0.8 * p.residue / d FROM push p JOIN deg ON deg.v = p.v JOIN st ON st.v = p.v WHERE p.residue >= 1e-4 * d) GROUP BY i, q, v),
last AS (SELECT q, max(i) AS i FROM push GROUP BY q),
rk AS MATERIALIZED (SELECT p.q, p.v, d, row_number() OVER (PARTITION BY p.q ORDER BY round(reserve / d, 12) DESC, p.v) AS r FROM push p JOIN last ON last.q = p.q AND last.i = p.i JOIN deg ON deg.v = p.v WHERE reserve > 0),
closed AS (SELECT a.q, a.r, count(*) AS n FROM rk a JOIN st ON st.v = a.v JOIN rk b ON b.q = a.q AND b.v = st.nbr WHERE b.r < a.r GROUP BY a.q, a.r),
steps AS (SELECT rk.q, rk.r, sum(d) OVER w AS volume, sum(d) OVER w - 2 * sum(coalesce(n, 0)) OVER w AS cut FROM rk LEFT JOIN closed ON closed.q = rk.q AND closed.r = rk.r WINDOW w AS (PARTITION BY rk.q ORDER BY rk.r)),
scored AS (SELECT s.q, s.r, cut * 1.0 / nullif(least(volume, (SELECT count(*) FROM st) - volume), 0) AS c FROM steps s JOIN rk ON rk.q = s.q AND rk.v = s.q WHERE s.r >= rk.r),
cutoff AS (SELECT q, arg_min(r, (c, r)) AS r, min(c) AS c FROM scored WHERE c IS NOT NULL GROUP BY q)"""
put("sweep_cut", on("trade_q1", 5, lambda g, st, q, p, w: static.sweep_cut(g, q).select("q", "v", e9("conductance"))), S.query(S.graph("trade_q1"), S.picked(5), _SWEEP, select="SELECT rk.q, rk.v, CAST(round(c * 1e9) AS BIGINT) AS conductance_e9 FROM rk JOIN cutoff ON cutoff.q = rk.q WHERE rk.r <= cutoff.r"))
put("select_containing", on("trade_q1", 5, lambda g, st, q, p, w: static.select_containing(st.select((F.col("v") % 5).alias("set_id"), "v").distinct().withColumn("score", F.col("set_id") % 3), q)), S.query(S.graph("trade_q1"), S.picked(5), "f AS (SELECT DISTINCT v % 5 AS set_id, v, v % 5 % 3 AS score FROM st)", select="SELECT q, f.v, score FROM qs JOIN f ON f.set_id = q % 5"))
put("periodic_edges", lambda s, d: heuristics.periodic_edges(VIEWS["trade"](s, d)), f"WITH {S.graph('trade')} SELECT a.u, a.v, a.t AS start, b.t - a.t AS period FROM e a JOIN e b ON a.u = b.u AND a.v = b.v AND b.t > a.t JOIN e c ON c.u = a.u AND c.v = a.v AND c.t = 2 * b.t - a.t")
put("periodic_clique", lambda s, d: heuristics.periodic_clique(g := VIEWS["meet"](s, d).settled(), pick(g, 5)))
put("periodic_clique_trade", lambda s, d: heuristics.periodic_clique(g := VIEWS["trade"](s, d).settled(), pick(g, 5), 3, 2))
_WIN = "win AS MATERIALIZED (SELECT s.t AS w, e.u, e.v, e.t FROM e JOIN (SELECT DISTINCT t FROM e) s ON e.t >= s.t AND e.t < s.t + 3)"
put("windows", on("trade_q1", 5, lambda g, st, q, p, w: temporal.in_windows(g, 3)), f"WITH {S.graph('trade_q1')}, {_WIN} SELECT * FROM win")
put("persistent_degree", on("trade_q1", 5, lambda g, st, q, p, w: temporal.persistent_degree(g, 3)), f"WITH {S.graph('trade_q1')}, {_WIN} SELECT w, v, count(*) AS degree FROM (SELECT DISTINCT w, u AS v, v AS n FROM win UNION SELECT w, v, u FROM win) GROUP BY w, v")
_PERSISTENT = """pw AS (SELECT DISTINCT s.t AS w, e.u, e.v FROM e JOIN (SELECT DISTINCT t FROM e) s ON e.t >= s.t AND e.t < s.t + 3),
pb AS MATERIALIZED (SELECT w, u AS v, v AS n FROM pw UNION SELECT w, v, u FROM pw),
pc(i, v, alive) AS (SELECT 0, v, true FROM (SELECT DISTINCT v FROM pb) UNION ALL
  SELECT a.i + 1, a.v, count(*) FILTER (d >= 2) >= 2 FROM pc a LEFT JOIN (SELECT b.w, b.v, count(*) AS d FROM pb b JOIN pc x ON x.v = b.v AND x.alive JOIN pc y ON y.v = b.n AND y.alive GROUP BY b.w, b.v) g ON g.v = a.v
  WHERE a.alive AND (a.i = 0 OR EXISTS (SELECT 1 FROM pc z WHERE NOT z.alive)) GROUP BY a.i, a.v),
pin AS (SELECT v FROM pc WHERE alive AND i = (SELECT max(i) FROM pc))"""
put("persistent_core", graph_alone("meet", lambda g: temporal.persistent_core(g := g.settled(), pick(g, 5))), S.query(S.graph("meet"), S.picked(5), _PERSISTENT, S.component("SELECT q, v FROM qs, pin WHERE q IN (SELECT v FROM pin)"), select="SELECT q, v, false AS exact FROM comp"))
put("interval_pairs", graph_alone("meet", lambda g: temporal.in_windows(g.settled(), 2).groupBy("w", "u", "v").agg(F.count_distinct("t").alias("n")).where("n = 2").select("w", "u", "v")), f"WITH {S.graph('meet')} SELECT a.t AS w, a.u, a.v FROM e a JOIN e b ON a.u = b.u AND a.v = b.v AND b.t = a.t + 1")
_INTERVAL = """ip AS MATERIALIZED (SELECT a.t AS w, a.u, a.v FROM e a JOIN e b ON a.u = b.u AND a.v = b.v AND b.t = a.t + 1),
ib AS MATERIALIZED (SELECT w, u AS v, v AS nbr FROM ip UNION ALL SELECT w, v, u FROM ip),
iw(i, w, v, theta, alive) AS (SELECT DISTINCT 0, w, v, CAST(0 AS BIGINT), true FROM ib UNION ALL
  SELECT i + 1, w, v, level, n > level FROM (SELECT *, greatest(theta, min(n) OVER (PARTITION BY w)) AS level FROM (
    SELECT p.i, p.w, p.v, p.theta, count(x.v) AS n FROM iw p LEFT JOIN (SELECT o.w, ib.v FROM iw o JOIN ib ON ib.w = o.w AND ib.nbr = o.v WHERE o.alive) x ON x.w = p.w AND x.v = p.v WHERE p.alive GROUP BY p.i, p.w, p.v, p.theta))),
ic AS MATERIALIZED (SELECT w, v, theta AS core FROM iw WHERE NOT alive AND theta > 0),
io AS (SELECT q, arg_max(w, (core, -w)) AS w, max(core) AS k FROM ic JOIN qs ON qs.q = ic.v GROUP BY q),
found(q, w, v) AS (SELECT q, w, q FROM io UNION SELECT f.q, f.w, ib.nbr FROM found f JOIN io ON io.q = f.q JOIN ib ON ib.w = f.w AND ib.v = f.v JOIN ic ON ic.w = f.w AND ic.v = ib.nbr AND ic.core >= io.k)"""
put("interval_core", lambda s, d: temporal.best_interval(g := VIEWS["nation"](s, d).settled(), pick(g, 5), 2), S.query(S.graph("nation"), S.picked(5), _INTERVAL, select="SELECT f.q, f.v, io.k, f.w AS start FROM found f JOIN io ON io.q = f.q"))
_BURST = """bw AS MATERIALIZED (SELECT s.t * 2 + l - 1 AS w, e.u, e.v, count(*) AS m FROM e, (SELECT DISTINCT t FROM e) s, (VALUES (1), (2)) x(l) WHERE e.t >= s.t AND e.t < s.t + l GROUP BY s.t, l, e.u, e.v),
bt AS (SELECT s.t * 2 + l - 1 AS w, count(DISTINCT e.t) AS times FROM e, (SELECT DISTINCT t FROM e) s, (VALUES (1), (2)) x(l) WHERE e.t >= s.t AND e.t < s.t + l GROUP BY s.t, l),
bb AS MATERIALIZED (SELECT w, u AS v, v AS nbr, m FROM bw UNION ALL SELECT w, v, u, m FROM bw),
bp(i, w, v, alive, density) AS (SELECT DISTINCT 0, w, v, true, CAST(0 AS DOUBLE) FROM bb UNION ALL
  SELECT i + 1, w, v, d > CAST(2.2 AS DOUBLE) * den, den FROM (SELECT *, sum(d) OVER (PARTITION BY w) / CAST(2 AS DOUBLE) / count(*) OVER (PARTITION BY w) AS den FROM (
    SELECT p.i, p.w, p.v, CAST(coalesce(sum(x.m), 0) AS DOUBLE) AS d FROM bp p LEFT JOIN (SELECT o.w, bb.v, bb.m FROM bp o JOIN bb ON bb.w = o.w AND bb.nbr = o.v WHERE o.alive) x ON x.w = p.w AND x.v = p.v WHERE p.alive GROUP BY p.i, p.w, p.v))),
br AS (SELECT w, arg_max(i, (density, -i)) AS i FROM bp WHERE i > 0 GROUP BY w),
bs AS MATERIALIZED (SELECT bp.w, v, density / times AS score FROM bp JOIN br ON br.w = bp.w AND br.i = bp.i JOIN bt ON bt.w = bp.w),
bo AS (SELECT q, arg_max(w, (score, -w)) AS w FROM bs JOIN qs ON qs.q = bs.v GROUP BY q)"""
put("density_burst", on("trade_q1", 5, lambda g, st, q, p, w: temporal.density_burst(g, q, 2).select("q", "v", e9("score"))), S.query(S.graph("trade_q1"), S.picked(5), _BURST, select="SELECT bo.q, bs.v, CAST(round(score * 1e9) AS BIGINT) AS score_e9 FROM bo JOIN bs ON bs.w = bo.w"))
put("inefficiency_community", on("copurchase_q1", 4, lambda g, st, q, p, w: heuristics.inefficiency_community(g, q)))


def _two(s: SparkSession, d: str, view: str) -> tuple[TemporalGraph, list[int]]:
    g = VIEWS[view](s, d).settled()
    return g, [r["q"] for r in pick(g, 5).orderBy("q").limit(2).collect()]


def _joined(s: SparkSession, d: str) -> DataFrame:
    """The tree of two query vertices has both, and the connector that grows from it is connected and has them."""
    g, two = _two(s, d, "trade_q1")
    st = settle(g.static)
    tree = heuristics.query_tree(st, two)
    grown = settle(heuristics.inefficiency_community_multi(g, two))
    head = lambda df: df.select(F.lit(two[0]).alias("q"), "v")
    whole = lambda df, name: cores.component(st, head(df)).agg(((F.count("*") == F.lit(df.count())) & (F.count_if(F.col("v").isin(two)) == 2)).alias(name))
    return whole(tree, "tree").crossJoin(whole(grown, "grown"))  # single rows


put("query_tree", _joined, "SELECT true AS tree, true AS grown")
_IMULTI = """two AS (SELECT q FROM qs ORDER BY q LIMIT 2),
ip AS MATERIALIZED (SELECT a.u, a.v FROM e a JOIN e b ON a.u = b.u AND a.v = b.v AND b.t = a.t + 1 WHERE a.t = 23946),
ist AS MATERIALIZED (SELECT u AS v, v AS nbr FROM ip UNION SELECT v, u FROM ip),
ione AS MATERIALIZED (SELECT DISTINCT CAST(0 AS BIGINT) AS q, v, CAST(1 AS BIGINT) AS units FROM ist)"""
_IREACH = """reach(l, v) AS (SELECT l, (SELECT min(q) FROM two) FROM (SELECT unnest(range(1, (SELECT min(core) FROM imc WHERE v IN (SELECT q FROM two)) + 1)) AS l) UNION SELECT r.l, s.nbr FROM reach r JOIN ist s ON s.v = r.v JOIN imc ON imc.v = s.nbr AND imc.core >= r.l),
best AS (SELECT max(l) AS l FROM (SELECT l FROM reach WHERE v IN (SELECT q FROM two) GROUP BY l HAVING count(*) = 2))"""
put("interval_core_multi", lambda s, d: temporal.interval_core_multi(*_two(s, d, "nation"), (23946, 23947)), S.query(S.graph("nation"), S.picked(5), _IMULTI, S.peel("ione", "SELECT v, nbr, 1 AS x FROM ist", "imc"), _IREACH, select="SELECT reach.v, reach.l AS k FROM reach JOIN best ON best.l = reach.l"))
# measures, over the vertices of positive proximity as a set that both engines have
_SET = "s AS MATERIALIZED (SELECT q, v FROM w)"
_TOUCH = "touch AS MATERIALIZED (SELECT qs.q, e.u, e.v, e.t, a.v IS NOT NULL AS x, b.v IS NOT NULL AS y FROM qs CROSS JOIN e LEFT JOIN s a ON a.q = qs.q AND a.v = e.u LEFT JOIN s b ON b.q = qs.q AND b.v = e.v)"
put("temporal_density", on("copurchase_q1", 8, lambda g, st, q, p, w: metrics.temporal_density(g, w.select("q", "v")).select("q", F.coalesce(e9("density"), F.lit(-1)).alias("density_e9"))), _sql("copurchase_q1", 8, _SET, _TOUCH, select="SELECT n.q, coalesce(CAST(round(2.0 * m / nullif(n.n * (n.n - 1.0) * times, 0) * 1e9) AS BIGINT), -1) AS density_e9 FROM (SELECT q, count(*) AS n FROM s GROUP BY q) n LEFT JOIN (SELECT q, count(*) AS m, count(DISTINCT t) AS times FROM touch WHERE x AND y GROUP BY q) i ON i.q = n.q"))
put("temporal_conductance", on("copurchase_q1", 8, lambda g, st, q, p, w: metrics.temporal_conductance(g, w.select("q", "v")).select("q", e9("conductance"))), _sql("copurchase_q1", 8, _SET, _TOUCH, select="SELECT q, CAST(round(cut * 1.0 / nullif(least(own, total - own), 0) * 1e9) AS BIGINT) AS conductance_e9 FROM (SELECT q, count(*) FILTER (x <> y) AS cut, sum(x::INT + y::INT) AS own, 2 * count(*) AS total FROM touch GROUP BY q)"))
put("static_conductance", on("copurchase_q1", 8, lambda g, st, q, p, w: metrics.static_conductance(st, w.select("q", "v")).select("q", e9("conductance"))), _sql("copurchase_q1", 8, _SET, select="SELECT q, CAST(round(cut * 1.0 / nullif(least(own, total - own), 0) * 1e9) AS BIGINT) AS conductance_e9 FROM (SELECT s.q, count(*) AS own, count(*) FILTER (b.v IS NULL) AS cut, (SELECT count(*) FROM st) AS total FROM s JOIN st ON st.v = s.v LEFT JOIN s b ON b.q = s.q AND b.v = st.nbr GROUP BY s.q)"))
put("min_biased_degree", on("copurchase_q1", 8, lambda g, st, q, p, w: metrics.min_biased_degree(st, w, w.select("q", "v"))), _sql("copurchase_q1", 8, _SET, select="SELECT q, min(rho) AS rho FROM (SELECT s.q, s.v, CAST(coalesce(sum(w.units), 0) AS BIGINT) AS rho FROM s LEFT JOIN st ON st.v = s.v LEFT JOIN w ON w.q = s.q AND w.v = st.nbr GROUP BY s.q, s.v) GROUP BY q"))
put("overlap_scores", on("copurchase_q1", 8, lambda g, st, q, p, w: metrics.overlap_scores(w.select("q", "v"), w.where("v % 3 <> 0").select("q", "v")).select("q", e9("precision"), e9("recall"), e9("f1"))), _sql("copurchase_q1", 8, select="SELECT q, CAST(round(h * 1.0 / n * 1e9) AS BIGINT) AS precision_e9, CAST(round(h * 1.0 / nullif(h, 0) * 1e9) AS BIGINT) AS recall_e9, CAST(round(2.0 * h / (n + h) * 1e9) AS BIGINT) AS f1_e9 FROM (SELECT q, count(*) AS n, count(*) FILTER (v % 3 <> 0) AS h FROM w GROUP BY q)"))
put("average_rank", lambda s, d: metrics.average_rank(table(s, d, "orders").groupBy(F.col("o_orderpriority").alias("dataset"), F.col("o_orderstatus").alias("method")).agg(F.count("*").alias("value"))).select("method", e9("mean_rank")), "SELECT method, CAST(round(avg(r) * 1e9) AS BIGINT) AS mean_rank_e9 FROM (SELECT o_orderstatus AS method, rank() OVER (PARTITION BY o_orderpriority ORDER BY count(*)) AS r FROM orders GROUP BY o_orderpriority, o_orderstatus) GROUP BY method")
put("occurrence_deciles", lambda s, d: workloads.deciles(VIEWS["trade"](s, d)), f"WITH {S.graph('trade')} SELECT v, t_count, CAST(ntile(10) OVER (ORDER BY t_count, v) AS INTEGER) AS decile FROM (SELECT src AS v, count(DISTINCT t) AS t_count FROM arcs GROUP BY src)")
_CORE_LEVELS = "lv AS MATERIALIZED (SELECT qs.q, c.core AS k FROM qs JOIN sc c ON c.v = qs.q)"
_REPORT = "SELECT x.q, count(*) AS size, count(*) FILTER (coalesce(core.core, 0) < coalesce(mine.core, 0)) AS drifted, CAST(round(count(*) FILTER (coalesce(core.core, 0) < coalesce(mine.core, 0)) * 1.0 / count(*) * 1e9) AS BIGINT) AS share_e9 FROM sx x LEFT JOIN core ON core.q = x.q AND core.v = x.v LEFT JOIN core mine ON mine.q = x.q AND mine.v = x.q GROUP BY x.q"
put("drift_report", on("copurchase_q1", 8, lambda g, st, q, p, w: D.drift_report(st, w, static.static_core(g, q)).select("q", "size", "drifted", e9("share"))), _sql("copurchase_q1", 8, S.peel(), _ONES, S.peel("ones", name="sc"), _CORE_LEVELS, S.component("SELECT lv.q, sc.v FROM lv JOIN sc ON sc.core >= lv.k", "sx"), select=_REPORT))
# drift: a community of the vertices that weigh at least a hundredth, an optimum of those below a twentieth
_FOUND, _OPTIMUM = "units >= 10000000", "units < 50000000"
_DRIFT = f"""df AS MATERIALIZED (SELECT q, v FROM w WHERE {_FOUND}), du AS MATERIALIZED (SELECT q, v FROM w WHERE {_FOUND} OR {_OPTIMUM}),
dens AS MATERIALIZED (SELECT k, s.q, coalesce(m / nullif(n * times, 0), 0) AS f, n FROM (SELECT 'found' AS k, q, count(*)::DOUBLE AS n FROM df GROUP BY q UNION ALL SELECT 'union', q, count(*) FROM du GROUP BY q) s
  LEFT JOIN (SELECT 'found' AS k, a.q, count(*)::DOUBLE AS m, count(DISTINCT e.t) AS times FROM df a JOIN e ON e.u = a.v JOIN df b ON b.q = a.q AND b.v = e.v GROUP BY a.q UNION ALL SELECT 'union', a.q, count(*), count(DISTINCT e.t) FROM du a JOIN e ON e.u = a.v JOIN du b ON b.q = a.q AND b.v = e.v GROUP BY a.q) i USING (k, q)),
rides AS (SELECT a.q, b.f >= a.f AS rides FROM dens a JOIN dens b ON a.q = b.q AND a.k = 'found' AND b.k = 'union')"""
_LEAST = """least_of AS (SELECT 'found' AS k, q, min(rho) AS rho FROM (SELECT a.q, a.v, coalesce(sum(w.units) FILTER (b.v IS NOT NULL), 0) AS rho FROM df a JOIN st ON st.v = a.v LEFT JOIN df b ON b.q = a.q AND b.v = st.nbr LEFT JOIN w ON w.q = a.q AND w.v = st.nbr GROUP BY a.q, a.v) GROUP BY q
  UNION ALL SELECT 'union', q, min(rho) FROM (SELECT a.q, a.v, coalesce(sum(w.units) FILTER (b.v IS NOT NULL), 0) AS rho FROM du a JOIN st ON st.v = a.v LEFT JOIN du b ON b.q = a.q AND b.v = st.nbr LEFT JOIN w ON w.q = a.q AND w.v = st.nbr GROUP BY a.q, a.v) GROUP BY q),
worse AS (SELECT a.q FROM least_of a JOIN least_of b ON a.q = b.q AND a.k = 'found' AND b.k = 'union' WHERE b.rho <= a.rho)"""
put("drift_density", on("copurchase_q1", 8, lambda g, st, q, p, w: D.burst_densities(g, w.where(_FOUND)).select("q", e9("density"))), _sql("copurchase_q1", 8, _DRIFT, select="SELECT q, CAST(round(f * 1e9) AS BIGINT) AS density_e9 FROM dens WHERE k = 'found'"))
put("free_riders", on("copurchase_q1", 8, lambda g, st, q, p, w: D.free_riders(g, w.where(_OPTIMUM), w.where(_FOUND))), _sql("copurchase_q1", 8, _DRIFT, select="SELECT q, rides FROM rides"))
put("drifted_members", on("copurchase_q1", 8, lambda g, st, q, p, w: D.drifted_members(g, st, w, w.where(_OPTIMUM), w.where(_FOUND))), _sql("copurchase_q1", 8, _DRIFT, _LEAST, select="SELECT q, v FROM du WHERE (q, v) NOT IN (SELECT (q, v) FROM df) AND q IN (SELECT q FROM rides WHERE rides) AND q IN (SELECT q FROM worse)"))
put("interval_degree", graph_alone("meet", lambda g: D.interval_degrees(g, g.slice(473370, 473371).static.select(F.lit(0).cast("bigint").alias("q"), "v").distinct(), 473370, 473370)), f"WITH {S.graph('meet')} SELECT CAST(0 AS BIGINT) AS q, min(d) AS degree FROM (SELECT src, count(DISTINCT dst) AS d FROM arcs WHERE t = 473370 GROUP BY src) HAVING count(*) > 0")
put("true_ratio", on("copurchase_q1", 8, lambda g, st, q, p, w: metrics.true_ratio(exact.from_weights(st, w, q).select("q", F.col("beta").alias("rho")).distinct(), metrics.min_biased_degree(st, w, w.where(_FOUND))).select("q", F.coalesce(e9("ratio"), F.lit(-1)).alias("ratio_e9"))), _sql("copurchase_q1", 8, S.peel(), S.exact(), _DRIFT, _LEAST, select="SELECT own.q, coalesce(CAST(round(own.beta * 1.0 / nullif(rho, 0) * 1e9) AS BIGINT), -1) AS ratio_e9 FROM own JOIN least_of l ON l.q = own.q AND l.k = 'found'"))
put("expanded_share", on("copurchase_q1", 8, lambda g, st, q, p, w: metrics.expanded_share(g, w.groupBy("q").agg(F.count("*").alias("expanded"))).select("q", e9("share"))), _sql("copurchase_q1", 8, select="SELECT q, CAST(round(count(*) * 1.0 / (SELECT count(DISTINCT v) FROM st) * 1e9) AS BIGINT) AS share_e9 FROM w GROUP BY q"))


def _timed(s: SparkSession, d: str) -> DataFrame:
    """name, positive: wall seconds of two actions."""
    g, st, q, _, w = _base(s, d, "copurchase_q1", 8)
    rows = [(name, metrics.timed(make)[1] > 0) for name, make in (("exact", lambda: exact.from_weights(st, w, q)), ("core", lambda: static.static_core(g, q)))]
    return s.createDataFrame(rows, "name string, positive boolean")


put("wall_seconds", _timed, "SELECT 'exact' AS name, true AS positive UNION ALL SELECT 'core', true")
put("array_memory", on("copurchase_q1", 8, lambda g, st, q, p, w: metrics.array_bytes(g, q).groupBy().agg(F.count("*").alias("n"), (F.max(F.when(F.col("method") != "graph", F.col("largest"))) < 2 * F.max(F.when(F.col("method") == "graph", F.col("bytes")))).alias("below_twice"))), "SELECT CAST(3 AS BIGINT) AS n, true AS below_twice")
put("no_drift", on("copurchase_q1", 8, lambda g, st, q, p, w: D.no_drift(st, w, (c := settle(exact.from_weights(st, w, q))), static.static_core(g, q)).join(c.where("beta > 0").select("q").distinct(), "q", "left_semi")), _sql("copurchase_q1", 8, S.peel(), S.exact(), select="SELECT q, true AS holds FROM own WHERE beta > 0"))
put("memory_report", on("copurchase_q1", 8, lambda g, st, q, p, w: metrics.memory_report(g, weights=w)), _sql("copurchase_q1", 8, select="SELECT 'graph' AS name, count(*) AS n_rows, count(*) * 24 AS bytes FROM e UNION ALL SELECT 'weights', count(*), count(*) * 24 FROM w"))
for _w in ("effectiveness", "approximation", "alpha_sweep", "scalability", "ablation", "case_study", "runtimes", "memory", "rank_sweep"):
    put(f"workload_{_w}", getattr(workloads, _w))

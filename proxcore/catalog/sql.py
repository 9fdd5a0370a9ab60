"""Pieces of the oracle's SQL. Recursion does there what rounds of joins do here."""

from __future__ import annotations

from proxcore.sources.views import EDGE_SQL

WEIGHTS = {"reciprocal": "(1.0 / ({0}))", "log": "(1.0 / log2(1.0 + ({0})))", "exp": "exp(-0.1 * ({0}))"}


def graph(view: str, decay: str = "reciprocal") -> str:
    """e, arcs, st, occ, nm."""
    w = WEIGHTS[decay].format("b.t - a.t")
    return f"""e AS MATERIALIZED ({EDGE_SQL[view]}),
arcs AS MATERIALIZED (SELECT u AS src, v AS dst, t FROM e UNION ALL SELECT v, u, t FROM e),
st AS MATERIALIZED (SELECT DISTINCT src AS v, dst AS nbr FROM arcs),
occ AS MATERIALIZED (SELECT src AS v, t, count(*) AS n_out FROM arcs GROUP BY src, t),
nm AS MATERIALIZED (SELECT occ.v, occ.t, occ.n_out, s.norm FROM occ LEFT JOIN (SELECT a.v, a.t, sum(b.n_out * {w}) AS norm FROM occ a JOIN occ b ON a.v = b.v AND b.t > a.t GROUP BY a.v, a.t) s ON s.v = occ.v AND s.t = occ.t)"""


def picked(k: int) -> str:
    """qs: the k vertices of the least hash."""
    return f"qs AS MATERIALIZED (SELECT v AS q FROM (SELECT DISTINCT v FROM st) ORDER BY ((v % 2147483648) * 2654435761) % 4294967296, v LIMIT {k})"


def prox(alpha: float = 0.2, decay: str = "reciprocal") -> str:
    """walk, prox, w (whole units)."""
    w = WEIGHTS[decay].format("a.t - r.t")
    return f"""walk(i, q, v, t, mass) AS (
  SELECT 1, q, dst, t, sum(1.0 / n) FROM (SELECT q, dst, t, count(*) OVER (PARTITION BY q) AS n FROM qs JOIN arcs ON src = q) GROUP BY q, dst, t
  UNION ALL
  SELECT r.i + 1, r.q, a.dst, a.t, sum({1 - alpha} * r.mass / m.norm * {w}) FROM walk r JOIN nm m ON m.v = r.v AND m.t = r.t AND m.norm IS NOT NULL JOIN arcs a ON a.src = r.v AND a.t > r.t GROUP BY r.i, r.q, a.dst, a.t),
prox AS MATERIALIZED (SELECT q, walk.v, sum(mass * CASE WHEN norm IS NULL THEN 1 ELSE {alpha} END) AS prox FROM walk JOIN nm ON nm.v = walk.v AND nm.t = walk.t GROUP BY q, walk.v),
w AS MATERIALIZED (SELECT q, v, CAST(round(prox * 1e9) AS BIGINT) AS units FROM prox WHERE round(prox * 1e9) > 0)"""


def peel(weights: str = "w", edges: str = "SELECT v, nbr, 1 AS x FROM st", name: str = "core") -> str:
    """name (q, v, core): levels at which vertices fall when all of the least biased degree go at once."""
    return f"""{name}_adj AS MATERIALIZED ({edges}),
{name}_peel(i, q, v, theta, alive) AS (
  SELECT DISTINCT 0, q, a.v, CAST(0 AS BIGINT), true FROM {weights} JOIN {name}_adj a ON a.nbr = {weights}.v
  UNION ALL
  SELECT i + 1, q, v, level, rho > level FROM (
    SELECT *, greatest(theta, min(rho) OVER (PARTITION BY q)) AS level FROM (
      SELECT p.i, p.q, p.v, p.theta, CAST(coalesce(sum(n.units * n.x), 0) AS BIGINT) AS rho
      FROM {name}_peel p LEFT JOIN (SELECT o.q, a.v, c.units, a.x FROM {name}_peel o JOIN {weights} c ON c.q = o.q AND c.v = o.v JOIN {name}_adj a ON a.nbr = o.v WHERE o.alive) n ON n.q = p.q AND n.v = p.v
      WHERE p.alive GROUP BY p.i, p.q, p.v, p.theta))),
{name} AS MATERIALIZED (SELECT q, v, theta AS core FROM {name}_peel WHERE NOT alive AND theta > 0)"""


def component(inside: str, name: str = "comp", edges: str = "st") -> str:
    """name (q, v): what is joined to the query within the rows (q, v) of inside."""
    return f"""{name}_in AS MATERIALIZED ({inside}),
{name}(q, v) AS (SELECT q, v FROM {name}_in WHERE q = v UNION SELECT c.q, s.nbr FROM {name} c JOIN {edges} s ON s.v = c.v JOIN {name}_in m ON m.q = c.q AND m.v = s.nbr)"""


def exact() -> str:
    """own (q, beta), comp (q, v)."""
    inside = "SELECT own.q, core.v FROM own JOIN core ON core.q = own.q WHERE beta > 0 AND core >= beta UNION ALL SELECT own.q, s.v FROM own, (SELECT DISTINCT v FROM st) s WHERE beta = 0"
    return f"own AS MATERIALIZED (SELECT qs.q, coalesce(core, 0) AS beta FROM qs LEFT JOIN core ON core.q = qs.q AND core.v = qs.q),\n{component(inside)}"


def query(*ctes: str, select: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(ctes) + "\n" + select

"""The experiments on the given tables: (spark, sf_dir) -> a table of results. Seconds are wall times of this session."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from proxcore import compact, cores, drift, exact, local, metrics
from proxcore.baselines import heuristics, static, temporal
from proxcore.graph import TemporalGraph, portable_hash
from proxcore.proximity import prepared, prox_hops
from proxcore.runtime import settle
from proxcore.sources.tables import table
from proxcore.sources.views import VIEWS
from proxcore.transitions import norms

ALPHAS = (0.1, 0.2, 0.4, 0.6, 0.8)
VIEW, QUERIES = "copurchase_q1", 6


def draw(g: TemporalGraph, k: int = 50) -> DataFrame:
    """q: of the largest component the k vertices of the least hash."""
    labels = settle(cores.connected_components(settle(g.static)))
    top = labels.groupBy("label").count().orderBy(F.desc("count"), "label").limit(1).select("label")
    return labels.join(F.broadcast(top), "label", "left_semi").orderBy(portable_hash(F.col("v")), "v").limit(k).select(F.col("v").alias("q"))


def deciles(g: TemporalGraph) -> DataFrame:
    """v, t_count, decile of the number of times. One global order: the window runs on one task over (v, t_count) alone."""
    return g.vertex_stats().select("v", "t_count", F.ntile(10).over(Window.orderBy("t_count", "v")).alias("decile"))


class Setting:
    """A settled view with its queries, proximity and units. Proximity and the static form are those of the queries' components,
    where a graph has more than a task takes: no walk and no community leaves them."""

    def __init__(self, s: SparkSession, d: str, view: str = VIEW, k: int = QUERIES, alpha: float = 0.2):
        self.name = view
        self.g, self.states = prepared(VIEWS[view](s, d))
        self.q = settle(draw(self.g, k))
        self.near = self.g if compact.ship(self.g) is not None else compact.near(self.g, self.q)
        compact.ship(self.near)  # so that no method's time has it
        self.static = settle(self.near.static)
        self.near_states = self.states if self.near is self.g else settle(norms(self.near))
        self.at(alpha)

    def at(self, alpha: float) -> Setting:
        """With another restart share."""
        self.alpha = alpha
        self.prox, self.prox_seconds = metrics.timed(lambda: settle(prox_hops(self.near, self.q, alpha, states=self.near_states)))
        self.weights = settle(cores.in_units(self.prox))
        self.exact = settle(exact.from_weights(self.static, self.weights, self.q))
        return self


def methods(x: Setting) -> dict[str, Callable[[], DataFrame]]:
    """Communities (q, v) of the model, its variants and the baselines."""
    return {
        "exact": lambda: exact.exact_community(x.g, x.q, x.alpha),
        "local": lambda: local.local_community(x.g, x.q, x.alpha),
        "floor k-core": lambda: static.floor_kcore(x.g, x.q, x.alpha, 2),
        "static core": lambda: static.static_core(x.g, x.q),
        "truss": lambda: static.truss_community(x.g, x.q),
        "sweep cut": lambda: static.sweep_cut(x.g, x.q, x.alpha),
        "periodic clique": lambda: heuristics.periodic_clique(x.g, x.q, 2, 2),
        "persistent core": lambda: temporal.persistent_core(x.g, x.q, 7, 2, 2),
        "density burst": lambda: temporal.density_burst(x.g, x.q, 1),
        "inefficiency": lambda: heuristics.inefficiency_community(x.g, x.q),
        "interval core": lambda: temporal.best_interval(x.g, x.q, 1),
    }


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def effectiveness(s: SparkSession, d: str) -> DataFrame:
    """method, n, conductance, density, rho: means over the queries that a method answers."""
    x = Setting(s, d)
    rows = []
    for name, make in methods(x).items():
        c = settle(make().select("q", "v"))
        one = metrics.temporal_conductance(x.g, c).join(metrics.temporal_density(x.g, c), "q", "full").join(metrics.min_biased_degree(x.static, x.weights, c), "q", "full")
        rows.append(one.agg(F.count("*").alias("n"), F.avg("conductance").alias("conductance"), F.avg("density").alias("density"), F.avg(F.col("rho") / 1e9).alias("rho")).select(F.lit(name).alias("method"), "*"))
    return _union(rows)


def runtimes(s: SparkSession, d: str) -> DataFrame:
    """method, seconds (a query, mean), place: the temporal methods."""
    x = Setting(s, d)
    n = max(1, x.q.count())
    rows = [(name, metrics.timed(make)[1] / n) for name, make in methods(x).items() if name not in ("static core", "truss", "sweep cut")]
    out = s.createDataFrame(rows, "method string, seconds double")
    return out.select("method", "seconds", F.rank().over(Window.orderBy("seconds")).alias("place"))  # a row for each method


def approximation(s: SparkSession, d: str) -> DataFrame:
    """q, eps, true_ratio, precision, recall, f1, expanded."""
    x = Setting(s, d)
    found = settle(local.local_community(x.g, x.q, x.alpha))
    best = x.exact.select("q", F.col("beta").alias("rho")).distinct()
    ratio = metrics.true_ratio(best, metrics.min_biased_degree(x.static, x.weights, found)).withColumnRenamed("ratio", "true_ratio")
    return found.select("q", "eps", "expanded").distinct().join(ratio, "q").join(metrics.overlap_scores(found, x.exact), "q")


def alpha_sweep(s: SparkSession, d: str) -> DataFrame:
    """alpha, rho, true_ratio, share (expanded), exact_seconds, local_seconds: means over queries."""
    rows = []
    setting = Setting(s, d, k=5, alpha=ALPHAS[0])
    for alpha in ALPHAS:
        x = setting if alpha == setting.alpha else setting.at(alpha)
        found, seconds = metrics.timed(lambda x=x: settle(local.local_community(x.g, x.q, x.alpha)))
        best = x.exact.select("q", F.col("beta").alias("rho")).distinct()
        ratio = metrics.true_ratio(best, metrics.min_biased_degree(x.static, x.weights, found))
        share = metrics.expanded_share(x.g, found)
        rows.append(best.join(ratio, "q").join(share, "q").agg((F.avg("rho") / 1e9).alias("rho"), F.avg("ratio").alias("true_ratio"), F.avg("share").alias("share")).select(F.lit(alpha).alias("alpha"), "*", F.lit(x.prox_seconds / 5).alias("exact_seconds"), F.lit(seconds / 5).alias("local_seconds")))
    return _union(rows)


def rank_sweep(s: SparkSession, d: str) -> DataFrame:
    """decile, n, share (expanded), exact_seconds, local_seconds: two queries of each other decile of the number of times."""
    g = VIEWS[VIEW](s, d).settled()
    compact.ship(g)
    ranked = settle(deciles(g))
    rows = []
    for tenth in (1, 4, 7, 10):
        q = settle(ranked.where(F.col("decile") == tenth).orderBy(portable_hash(F.col("v")), "v").limit(2).select(F.col("v").alias("q")))
        _, a = metrics.timed(lambda q=q: exact.exact_community(g, q))
        found, b = metrics.timed(lambda q=q: settle(local.local_community(g, q)))
        rows.append(metrics.expanded_share(g, found).agg(F.count("*").alias("n"), F.avg("share").alias("share")).select(F.lit(tenth).alias("decile"), "*", F.lit(a / 2).alias("exact_seconds"), F.lit(b / 2).alias("local_seconds")))
    return _union(rows)


def scalability(s: SparkSession, d: str) -> DataFrame:
    """by, percent, m, exact_seconds: the exact method on samples of vertices or edges."""
    whole = VIEWS["trade_q1"](s, d).settled()
    rows = []
    for by in ("vertex", "edge"):
        for percent in (20, 60, 100):
            g = whole.sample(percent, by).settled() if percent < 100 else whole
            q = settle(g.static.select("v").distinct().orderBy(portable_hash(F.col("v")), "v").limit(2).select(F.col("v").alias("q")))
            _, seconds = metrics.timed(lambda g=g, q=q: exact.exact_community(g, q))
            rows.append((by, percent, g.edges.count(), seconds / 2))
    return s.createDataFrame(rows, "by string, percent int, m bigint, exact_seconds double")


def memory(s: SparkSession, d: str) -> DataFrame:
    """name, n_rows, bytes: the graph and what both methods hold."""
    x = Setting(s, d)
    members, lower, _ = local.expand_levels(x.g, x.q, x.alpha)
    return metrics.memory_report(x.g, states=x.states, exact_scores=x.prox, local_members=members, local_lower=lower)


def ablation(s: SparkSession, d: str) -> DataFrame:
    """prune, stop, expanded, seconds: means, with bounds switched off in turn."""
    x = Setting(s, d, k=5)
    rows = []
    for prune in (True, False):
        for stop in (True, False):
            found, seconds = metrics.timed(lambda p=prune, t=stop: settle(local.local_community(x.g, x.q, x.alpha, prune=p, stop=t)))
            rows.append(found.select("q", "expanded").distinct().agg(F.avg("expanded").alias("expanded")).select(F.lit(prune).alias("prune"), F.lit(stop).alias("stop"), "expanded", F.lit(seconds / 5).alias("seconds")))
    return _union(rows)


def case_study(s: SparkSession, d: str) -> DataFrame:
    """method, q, v, name, drifted: members by name for one part, and which of them drifted."""
    x = Setting(s, d, k=1)
    names = table(s, d, "part").select(F.col("p_partkey").alias("v"), F.col("p_name").alias("name"))
    levels = cores.core_numbers(x.static, x.weights)
    own = settle(levels.where("v = q").select("q", F.col("core").alias("beta")))
    rows = []
    every = methods(x)
    for name in ("exact", "floor k-core", "persistent core", "interval core"):
        c = every[name]().select("q", "v").join(levels, ["q", "v"], "left").join(own, "q", "left")
        rows.append(c.select(F.lit(name).alias("method"), "q", "v", (F.coalesce("core", F.lit(0)) < F.coalesce("beta", F.lit(0))).alias("drifted")))
    return _union(rows).join(names, "v").select("method", "q", "v", "name", "drifted")


def drift_shares(s: SparkSession, d: str) -> DataFrame:
    """method, size, share: how much of each method's communities drifted, mean over queries."""
    x = Setting(s, d)
    return _union([drift.drift_report(x.static, x.weights, settle(make().select("q", "v"))).agg(F.avg("size").alias("size"), F.avg("share").alias("share")).select(F.lit(name).alias("method"), "*") for name, make in methods(x).items()])

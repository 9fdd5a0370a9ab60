"""Graphs that fit a task, as arrays: the same results as the distributed methods, many queries in parallel.

The edge table is broadcast after its size and its work are checked (MOST_EDGES, MOST_PAIRS); `ship` gives None beyond, and
callers then take the distributed way. A method asked for by name then gets the edges of the queries' components (`near`), which
are all that a walk or a community can have; TooLarge says that these don't fit either. Each worker builds the arrays once and answers blocks of queries. States (v, t)
are in order of time, so one pass over the times sends all mass: within a time no state feeds another.
"""

from __future__ import annotations

import math
import uuid
import warnings
from collections.abc import Callable, Iterable, Iterator
from typing import TYPE_CHECKING

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxcore.graph import TemporalGraph
from proxcore.runtime import Growing, query_table, settle

if TYPE_CHECKING:
    from proxcore.slots import Slots

Decay = str | tuple[str, float]

#: Temporal edges of a broadcast graph; pairs of states of one vertex; numbers that a block of queries holds.
MOST_EDGES, MOST_PAIRS, MOST_CELLS = 1_000_000, 5_000_000, 8_000_000
#: The same for a graph by slots, whose edges aren't listed: members of all slots, and pairs of a vertex's slots.
MOST_MEMBERS, MOST_MEMBER_PAIRS = 2_000_000, 10_000_000
#: Bytes of the arrays of a graph that one task makes by itself (`alone`), where it is too large to be broadcast to all.
MOST_BYTES = 1_000_000_000
#: Rows that a task gathers before it sends them on.
BATCH_ROWS = 100_000


def _runs(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """start, start + 1, ... for each of the runs, one after the other."""
    ends = np.cumsum(sizes)
    return np.arange(ends[-1] if len(ends) else 0) - np.repeat(ends - sizes - starts, sizes)


def _weight(dt: np.ndarray, decay: Decay) -> np.ndarray:
    if decay == "reciprocal":
        return 1.0 / dt
    return 1.0 / np.log2(1.0 + dt) if decay == "log" else np.exp(-float(decay[1]) * dt)


class Arrays:
    """Vertices count from 0 in order of their ids."""

    def __init__(self, u: np.ndarray, v: np.ndarray, t: np.ndarray, decay: Decay = "reciprocal"):
        self.ids, ends = np.unique(np.concatenate([u, v]), return_inverse=True)
        self.m, self.n = len(u), len(self.ids)
        src, dst = ends, np.concatenate([ends[self.m :], ends[: self.m]])
        times, at = np.unique(np.concatenate([t, t]), return_inverse=True)
        codes, leaves = np.unique(at * self.n + src, return_inverse=True)
        enters = np.searchsorted(codes, at * self.n + dst)
        by_end = np.argsort(enters, kind="stable")
        self.arc_src, self.arc_from, self.arc_to = src[by_end], leaves[by_end], enters[by_end]
        self.state_v, time_of = codes % self.n, codes // self.n
        n_out = np.bincount(leaves, minlength=len(codes))
        # pairs of an earlier and a later state of one vertex
        self.by_vertex = np.argsort(self.state_v, kind="stable")
        held = np.bincount(self.state_v, minlength=self.n)
        self.first_state = np.cumsum(held) - held
        place = np.arange(len(codes))
        later = np.repeat(self.first_state + held, held) - place - 1
        early, late = self.by_vertex[np.repeat(place, later)], self.by_vertex[_runs(place + 1, later)]
        g = _weight((times[time_of[late]] - times[time_of[early]]).astype(np.float64), decay)
        norm = np.bincount(early, n_out[late] * g, len(codes))
        by_late = np.argsort(late, kind="stable")
        self.early, self.late, self.share = early[by_late], late[by_late], (g / norm[early])[by_late]
        self.dangling = np.empty(len(codes), bool)
        self.dangling[self.by_vertex] = later == 0
        self.state_at = np.searchsorted(time_of, np.arange(len(times) + 1))
        self.pair_at, self.arc_at = np.searchsorted(self.late, self.state_at), np.searchsorted(self.arc_to, self.state_at)
        self.arc_head = np.searchsorted(self.arc_to, np.arange(len(codes)))
        # the graph without times; w counts a pair's temporal edges
        flat, self.w = np.unique(src * self.n + dst, return_counts=True)
        self.x, self.y = flat // self.n, flat % self.n
        self.degree = np.bincount(self.x, minlength=self.n)
        self.first = np.cumsum(self.degree) - self.degree

    def nbytes(self) -> int:
        """Of the graph's arrays."""
        return sum(x.nbytes for x in vars(self).values() if isinstance(x, np.ndarray))

    def at(self, q: int) -> int | None:
        k = int(np.searchsorted(self.ids, q))
        return k if k < self.n and self.ids[k] == q else None

    def _edges_of(self, vs: np.ndarray) -> np.ndarray:
        return _runs(self.first[vs], self.degree[vs])

    def proximity(self, qs: list[int], alpha: float) -> np.ndarray:
        """A column for each query."""
        mass = np.zeros((len(self.state_v), len(qs)))
        seeds = [self.by_vertex[self.first_state[q] : self.first_state[q] + np.count_nonzero(self.state_v == q)] for q in qs]
        seed_state, seed_col = np.concatenate(seeds), np.repeat(np.arange(len(qs)), [len(s) for s in seeds])
        out = np.array([np.count_nonzero(self.arc_src == q) for q in qs], np.float64)
        order = np.argsort(seed_state, kind="stable")
        seed_state, seed_col = seed_state[order], seed_col[order]
        seed_at = np.searchsorted(seed_state, self.state_at)
        for k in range(len(self.state_at) - 1):
            low, high = self.state_at[k], self.state_at[k + 1]
            flow = np.zeros((high - low, len(qs)))
            p, r = self.pair_at[k], self.pair_at[k + 1]
            if p < r:
                late = self.late[p:r]
                heads = np.flatnonzero(np.r_[True, late[1:] != late[:-1]])
                flow[late[heads] - low] = (1 - alpha) * np.add.reduceat(self.share[p:r, None] * mass[self.early[p:r]], heads, axis=0)
            s = slice(seed_at[k], seed_at[k + 1])
            flow[seed_state[s] - low, seed_col[s]] += 1 / out[seed_col[s]]
            a, b = self.arc_at[k], self.arc_at[k + 1]
            mass[low:high] = np.add.reduceat(flow[self.arc_from[a:b] - low], self.arc_head[low:high] - a, axis=0)
        mass[~self.dangling] *= alpha
        return np.add.reduceat(mass[self.by_vertex], self.first_state, axis=0)

    def component(self, alive: np.ndarray, q: int) -> np.ndarray:
        """Vertices that members join to q, ascending."""
        seen = np.zeros(self.n, bool)
        seen[q] = True
        frontier = np.array([q])
        while len(frontier):
            near = self.y[self._edges_of(frontier)]
            frontier = np.unique(near[alive[near] & ~seen[near]])
            seen[frontier] = True
        return np.flatnonzero(seen)

    def _shave(self, units: np.ndarray, w: np.ndarray | None, rho: np.ndarray, alive: np.ndarray, floor: float, q: int | None, gone: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray] | None:
        """Biased degrees and members once all reach the floor; None if q goes."""
        rho, alive = rho.copy(), alive.copy()
        gone = np.flatnonzero(alive & (rho < floor)) if gone is None else gone
        while len(gone):
            alive[gone] = False
            if q is not None and not alive[q]:
                return None
            e = self._edges_of(gone)
            lost = np.repeat(units[gone], self.degree[gone]) * (1 if w is None else w[e])
            near = self.y[e]
            np.subtract.at(rho, near, lost)
            near = np.unique(near)
            gone = near[alive[near] & (rho[near] < floor)]
        return rho, alive

    def best_core(self, units: np.ndarray, q: int, w: np.ndarray | None = None) -> tuple[int, np.ndarray]:
        """The best smallest biased degree with q, by bisection over ever smaller cores, and its largest connected set."""
        rho = np.bincount(self.x, units[self.y] * (1 if w is None else w), self.n).astype(np.int64)
        alive, low, high = np.ones(self.n, bool), 0, int(rho[q])
        while low < high:
            mid = (low + high + 1) // 2
            if (found := self._shave(units, w, rho, alive, mid, q)) is None:
                high = mid - 1
            else:
                rho, alive = found
                low, high = int(rho[alive].min()), min(high, int(rho[q]))
        return low, self.component(alive, q)

    def floor_core(self, prox: np.ndarray, q: int, k: int) -> tuple[float, np.ndarray] | None:
        """The connected k-core with q of the largest smallest proximity; at floor 0 where only the plain k-core has q."""
        ones, alive = np.ones(self.n, np.int64), prox > 0
        degree = np.bincount(self.x[alive[self.y]], minlength=self.n)
        found = self._shave(ones, None, degree, alive, k, q) if alive[q] else None
        if found is None:
            found = self._shave(ones, None, self.degree, np.ones(self.n, bool), k, q)
            return None if found is None else (0.0, self.component(found[1], q))
        degree, alive = found
        levels = np.unique(prox[alive & (prox <= prox[q])])
        low, high = 0, len(levels) - 1
        while low < high:
            mid = (low + high + 1) // 2
            if (found := self._shave(ones, None, degree, alive, k, q, np.flatnonzero(alive & (prox < levels[mid])))) is None:
                high = mid - 1
            else:
                (degree, alive), low = found, mid
        return float(prox[alive].min()), self.component(alive, q)

    def _sums(self, values: np.ndarray, of: np.ndarray) -> np.ndarray:
        """Over the neighbours of each of the vertices of a mask; others may have any value."""
        return np.bincount(self.x, values[self.y], self.n)

    def _joins(self, members: np.ndarray, qs: np.ndarray) -> bool:
        """One component of the members has all of a set."""
        return bool(members[qs].all()) and (len(qs) == 1 or bool(np.isin(qs, self.component(members, int(qs[0]))).all()))

    def expand(self, q: int | np.ndarray, alpha: float, *, least: float | None = None, prune: bool = True, stop: bool = True, union: bool = False) -> tuple[np.ndarray, np.ndarray, dict]:
        """Members (a mask), lower bounds and facts of the expansion by levels; from a set of vertices, alike or (union) by their arcs."""
        least = 1 / self.m if least is None else least
        qs = np.atleast_1d(q)
        out = np.bincount(self.arc_src, minlength=self.n)
        start = np.zeros(self.n)
        start[qs] = 1.0 / out[qs].sum() if union else 1.0 / (out[qs] * len(qs))
        residue = start[self.arc_src]
        lower, members, visited, active = np.zeros(self.n), np.zeros(self.n, bool), np.zeros(self.n, bool), np.zeros(self.n, bool)
        visited[qs] = True
        queue, beta, left, reason, whole = qs, 0.0, 1.0, "exhausted", len(qs) == 1
        while len(queue):
            members[queue] = True
            active[:] = False
            active[queue] = True
            hot = np.flatnonzero((residue >= least) & active[self.arc_src])
            mass = np.bincount(self.arc_to[hot], residue[hot], len(self.state_v))
            residue[hot] = 0.0
            lower += np.bincount(self.state_v, np.where(self.dangling, mass, alpha * mass), self.n)
            flow = np.bincount(self.late, (1 - alpha) * self.share * mass[self.early], len(self.state_v))
            residue += flow[self.arc_from]
            left = float(residue.sum())
            inside = np.bincount(self.x, (lower * members)[self.y], self.n)
            whole = whole or self._joins(members, qs)
            beta = max(beta, float(inside[members].min())) if whole else beta
            near = self.y[self._edges_of(queue)]
            fresh = np.unique(near[~visited[near]])
            visited[fresh] = True
            queue = fresh[left + np.bincount(self.x, lower[self.y], self.n)[fresh] >= beta - 1e-12] if prune else fresh
            if stop and len(queue) and left + lower[queue].sum() < beta - 1e-12:
                members[queue] = True
                reason = "bound"
                break
        return members, lower, {"residue": left, "expanded": int(members.sum()), "visited": int(visited.sum()), "reason": reason}

    def shrink(self, members: np.ndarray, lower: np.ndarray, residue: float, q: int | np.ndarray, *, anchor: str = "max") -> tuple[float, np.ndarray]:
        """The certified ratio and its community: the ratio is halved while q survives, or one component holds all of a set."""
        alive, qs = members, np.atleast_1d(q)
        rho = self._sums(lower * alive, alive)
        target = float(rho[alive].max() if anchor == "max" else rho[qs].min()) + residue
        low = float(rho[alive].min())
        eps = target / low if low > 0 else math.inf
        ratio = target / rho[alive & (rho > 0)].min() if (alive & (rho > 0)).any() else 0.0  # a larger one removes the same vertices
        while ratio >= 1:
            # sums afresh in each round, so that they don't drift
            now = alive
            while True:
                kept = now & (ratio * self._sums(lower * now, now) >= target * (1 - 1e-12))
                if not kept[qs].all() or kept.sum() == now.sum():
                    break
                now = kept
            if not self._joins(kept, qs):
                break
            eps, alive, ratio = ratio, now, ratio / 2
        return eps, self.component(alive, int(qs[0]))


_held: dict[object, Arrays] = {}


def _arrays(sent: Broadcast, decay: Decay) -> Arrays:
    """One for each worker and graph."""
    name, *columns = sent.value
    if (key := (name, str(decay))) not in _held:
        from proxcore.slots import Slots

        _held.clear()
        _held[key] = Slots(*columns, decay) if len(columns) == 2 else Arrays(*columns, decay)
    return _held[key]


def ship(g: TemporalGraph) -> Broadcast | None:
    """The edges, broadcast once for each graph; None if they, or the pairs of states, are too many."""
    if "_shipped" not in g.__dict__:
        g.__dict__["_shipped"] = None
        table = g.edges.select("u", "v", "t").limit(MOST_EDGES + 1).toArrow()
        if table.num_rows <= MOST_EDGES:
            u, v, t = (table.column(c).to_numpy().astype(np.int64) for c in ("u", "v", "t"))
            states = pd.DataFrame({"v": np.concatenate([u, v]), "t": np.concatenate([t, t])}).drop_duplicates()
            held = states.groupby("v").size().to_numpy()
            if (held * (held - 1) // 2).sum() <= MOST_PAIRS:
                g.__dict__["_shipped"] = g.edges.sparkSession.sparkContext.broadcast((uuid.uuid4().hex, u, v, t))
    return g.__dict__["_shipped"]


def ship_slots(g: TemporalGraph) -> Broadcast | None:
    """The members of a graph's slots (`slots.Slots`), broadcast once; None if it has none, or these or the pairs of states are too many."""
    if "_shipped_slots" not in g.__dict__:
        g.__dict__["_shipped_slots"] = None
        table = None if g.slots is None else g.slots.limit(MOST_MEMBERS + 1).toArrow()
        if table is not None and table.num_rows <= MOST_MEMBERS:
            v, t = (table.column(c).to_numpy().astype(np.int64) for c in ("v", "t"))
            held = np.unique(v, return_counts=True)[1]
            if (held * (held - 1) // 2).sum() <= MOST_MEMBER_PAIRS:
                g.__dict__["_shipped_slots"] = g.spark.sparkContext.broadcast((uuid.uuid4().hex, v, t))
    return g.__dict__["_shipped_slots"]


def fits(g: TemporalGraph, queries: DataFrame | Iterable[int], *, by_slots: bool = True) -> bool:
    """A task takes the whole graph, by its edges or its slots, or the edges of the queries' components."""
    return by_slots and ship_slots(g) is not None or ship(g) is not None or ship(near(g, queries)) is not None


class TooLarge(ValueError):
    pass


def near(g: TemporalGraph, queries: DataFrame | Iterable[int]) -> TemporalGraph:
    """The edges of the components that have a query; found once for each graph and table of queries."""
    known = g.__dict__.setdefault("_near", {})
    key = id(queries) if isinstance(queries, DataFrame) else tuple(sorted(queries))
    if key not in known:
        known[key] = queries, _near(g, queries)  # the table stays, so that its id is no other's
    return known[key][1]


def _near(g: TemporalGraph, queries: DataFrame | Iterable[int]) -> TemporalGraph:
    static = settle(g.static)
    seen = Growing(query_table(g.edges.sparkSession, queries).select(F.col("q").alias("v")))
    frontier = seen.table
    while frontier.limit(1).count():
        reached = frontier.join(static, "v").select(F.col("nbr").alias("v")).distinct()
        frontier = seen.add(reached.join(seen.table, "v", "left_anti"))
    return TemporalGraph(settle(g.edges.join(seen.table.select(F.col("v").alias("u")), "u", "left_semi").select("u", "v", "t")))


def or_distributed(make: Callable[[], DataFrame]) -> DataFrame | None:
    """A method in tasks; None where the queries' components don't fit one, for callers that have another way to equal results."""
    try:
        return make()
    except TooLarge as e:
        warnings.warn(f"{e}: the distributed method runs instead", stacklevel=3)
        return None


def answer(g: TemporalGraph, queries: DataFrame | Iterable[int], decay: Decay, schema: str, one_block: Callable[[Arrays, list[int]], Iterator[dict]], *, by_slots: bool = False) -> DataFrame:
    """Rows of one_block(arrays, vertices), whose queries count from 0, for all queries that the graph has. by_slots: it takes Slots too."""
    sent = by_slots and ship_slots(g) or ship(g) or ship(near(g, queries))
    if sent is None:
        raise TooLarge(f"a task holds graphs of at most {MOST_EDGES} edges and {MOST_PAIRS} pairs of states; take a distributed method")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            if len(sent.value[1]):
                yield from _blocks(_arrays(sent, decay), batch["q"], schema, one_block)

    spark = g.spark
    spread = query_table(spark, queries).repartition(spark.sparkContext.defaultParallelism)
    return spread.mapInPandas(run, schema)


def _blocks(a: Arrays, queries: Iterable[int], schema: str, one_block: Callable[[Arrays, list[int]], Iterator[dict]]) -> Iterator[pd.DataFrame]:
    names = [part.split()[0] for part in schema.split(", ")]
    own = [k for q in queries if (k := a.at(int(q))) is not None]
    width = max(1, MOST_CELLS // len(a.state_v))
    for low in range(0, len(own), width):
        for rows in one_block(a, own[low : low + width]):
            yield pd.DataFrame(rows, columns=names)


def lengths(g: TemporalGraph) -> dict[str, int]:
    """What the arrays of a graph count, without making them: m edges, n vertices, states, pairs of a vertex's states, times and static arcs."""
    held = g.arcs.select("src", "t").distinct().groupBy("src").agg(F.count("*").alias("h"))
    one = held.agg(F.count("*").alias("n"), F.coalesce(F.sum("h"), F.lit(0)).alias("states"), F.coalesce(F.sum(F.expr("h * (h - 1) div 2")), F.lit(0)).alias("pairs"))
    times = g.edges.agg(F.count("*").alias("m"), F.count_distinct("t").alias("times"))
    return one.crossJoin(times).crossJoin(g.static.agg(F.count("*").alias("arcs"))).first().asDict()  # single rows


def bytes_of(x: dict[str, int]) -> int:
    """Arrays.nbytes() of a graph of these lengths, by Arrays.__init__; eight bytes a number but for the flags of states."""
    return 8 * (4 * x["n"] + 6 * x["m"] + 3 * x["states"] + 3 * x["pairs"] + 3 * (x["times"] + 1) + 3 * x["arcs"]) + x["states"]


def alone(g: TemporalGraph, queries: DataFrame | Iterable[int], decay: Decay, schema: str, one_block: Callable[[Arrays, list[int]], Iterator[dict]]) -> DataFrame:
    """As answer, for a graph too large for it whose arrays take MOST_BYTES at most: one task gets the edges by a shuffle and makes them, once."""
    if (size := bytes_of(lengths(g))) > MOST_BYTES:
        raise TooLarge(f"the arrays of the graph take {size} bytes, of {MOST_BYTES} at most")

    def run(edges: pd.DataFrame, asked: pd.DataFrame) -> pd.DataFrame:
        names = [part.split()[0] for part in schema.split(", ")]
        if not len(edges) or not len(asked):
            return pd.DataFrame([], columns=names)
        a = Arrays(*(edges[c].to_numpy(np.int64) for c in ("u", "v", "t")), decay)
        return pd.concat([pd.DataFrame([], columns=names), *_blocks(a, asked["q"], schema, one_block)])

    one = F.lit(0).alias("one")
    return g.edges.select(one, "u", "v", "t").groupBy("one").cogroup(query_table(g.spark, queries).select(one, "q").groupBy("one")).applyInPandas(run, schema)


def proximity(g: TemporalGraph, queries: DataFrame | Iterable[int], alpha: float = 0.2, *, decay: Decay = "reciprocal") -> DataFrame:
    """q, v, prox."""

    def block(a: Arrays, qs: list[int]) -> Iterator[dict]:
        prox = a.proximity(qs, alpha)
        for k, q in enumerate(qs):
            has = np.flatnonzero(prox[:, k])
            yield {"q": a.ids[q], "v": a.ids[has], "prox": prox[has, k]}

    return answer(g, queries, decay, "q bigint, v bigint, prox double", block, by_slots=True)


def exact(g: TemporalGraph, queries: DataFrame | Iterable[int], alpha: float, *, decay: Decay, unit: int) -> DataFrame:
    """q, v, beta."""

    def block(a: Arrays, qs: list[int]) -> Iterator[dict]:
        units = np.floor(a.proximity(qs, alpha) * unit + 0.5).astype(np.int64)
        for k, q in enumerate(qs):
            beta, found = a.best_core(np.ascontiguousarray(units[:, k]), q)
            yield {"q": a.ids[q], "v": a.ids[found], "beta": beta / unit}

    return answer(g, queries, decay, "q bigint, v bigint, beta double", block, by_slots=True)


def static(g: TemporalGraph) -> DataFrame | None:
    """v, nbr of a graph that ship_slots takes, else None: each vertex's neighbours from its slots, so that a pair that meets often is made once
    for each end and no pair is shuffled."""
    if (sent := ship_slots(g)) is None:
        return None

    def batch(a: Slots, vs: list[int], near: list[np.ndarray]) -> pa.RecordBatch:
        both = np.repeat(a.ids[vs], [len(x) for x in near]), a.ids[np.concatenate(near)]
        return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in both], ["v", "nbr"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in batches:
            a = _arrays(sent, "reciprocal")
            vs, near, n = [], [], 0
            for k in map(a.at, part.column("v").to_pylist()):
                if k is None:
                    continue
                vs.append(k)
                near.append(a.neighbours(k))
                n += len(near[-1])
                if n >= BATCH_ROWS:
                    yield batch(a, vs, near)
                    vs, near, n = [], [], 0
            if n:
                yield batch(a, vs, near)

    return g.slots.select("v").repartition(4 * g.spark.sparkContext.defaultParallelism, "v").distinct().mapInArrow(run, "v bigint, nbr bigint")


def _weighted(g: TemporalGraph, queries: DataFrame, weights: DataFrame, schema: str, one: Callable[..., dict], *more: str) -> DataFrame:
    """Rows of one(slots, query, its units, vertices with units), a task for each query of a graph that ship_slots takes; weights (q, v, units).
    more: further columns of numbers, which one() gets as units, after the rest."""
    sent = ship_slots(g)
    names = [part.split()[0] for part in schema.split(", ")]

    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        a = _arrays(sent, "reciprocal")
        if (q := a.at(int(key[0]))) is None:
            return pd.DataFrame([], columns=names)
        own = pdf.dropna(subset=["v"])
        at, units = np.searchsorted(a.ids, own["v"].to_numpy(np.int64)), np.zeros(a.n, np.int64)
        units[at] = own["units"].to_numpy(np.int64)
        others = np.zeros((len(more), a.n))
        others[:, at] = own[list(more)].to_numpy(np.float64).T
        return pd.DataFrame(one(a, q, units, at, *others), columns=names)

    rows = queries.select("q").join(weights.select("q", "v", "units", *more), "q", "left")
    return rows.repartition(g.spark.sparkContext.defaultParallelism, "q").groupBy("q").applyInPandas(run, schema)


def core_numbers(g: TemporalGraph, weights: DataFrame) -> DataFrame:
    """q, v, core, as cores.core_numbers; vertices of core 0 have no row."""

    def one(a: Slots, q: int, units: np.ndarray, _: np.ndarray) -> dict:
        core = a.core_numbers(units)
        has = np.flatnonzero(core)
        return {"q": a.ids[q], "v": a.ids[has], "core": core[has]}

    return _weighted(g, weights.select("q").distinct(), weights, "q bigint, v bigint, core bigint", one)


def from_weights(g: TemporalGraph, weights: DataFrame, queries: DataFrame) -> DataFrame:
    """q, v, beta (units), as exact.from_weights."""

    def one(a: Slots, q: int, units: np.ndarray, _: np.ndarray) -> dict:
        beta, found = a.best_core(units, q)
        return {"q": a.ids[q], "v": a.ids[found], "beta": beta}

    return _weighted(g, queries, weights, "q bigint, v bigint, beta bigint", one)


def smallest_degree(g: TemporalGraph, weights: DataFrame, members: DataFrame) -> DataFrame:
    """q, rho: the smallest biased degree of each query's members, as metrics.min_biased_degree."""

    def one(a: Slots, q: int, units: np.ndarray, inside: np.ndarray) -> dict:
        return {"q": [a.ids[q]], "rho": [a.degrees(units, inside)[inside].min()]}

    inside = members.select("q", "v").join(weights, ["q", "v"], "left").select("q", "v", F.coalesce("units", F.lit(0)).alias("units"))
    return _weighted(g, members.select("q").distinct(), inside, "q bigint, rho bigint", one)


def certificate(g: TemporalGraph, prox: DataFrame, weights: DataFrame, queries: DataFrame, alpha: float = 0.2, *, unit: int = 10**9, **how: bool) -> DataFrame:
    """q, bounds, covered, ratio: whether the true biased degrees (from prox) of all expanded vertices lie within the bounds, the exact community
    (from weights) is expanded, and the smallest biased degree found is within the certified ratio of the exact one."""

    def one(a: Slots, q: int, units: np.ndarray, _: np.ndarray, p: np.ndarray) -> dict:
        members, lower, facts = a.expand(q, alpha, **how)
        inside = np.flatnonzero(members)
        low, rho = (a.degrees(x * members, inside)[inside] for x in (lower, p))
        best, community = a.best_core(units, q)
        eps, found = a.shrink(members, lower, facts["residue"], q)
        kept = np.zeros(a.n, np.int64)
        kept[found] = units[found]
        beta, best = a.degrees(kept, found)[found].min() / unit, best / unit
        bounds = (low <= rho + 1e-9) & (rho <= low + facts["residue"] + 1e-9)
        return {"q": [a.ids[q]], "bounds": [bool(bounds.all())], "covered": [bool(best == 0 or members[community].all())], "ratio": [bool(beta <= best + 1e-7 and best <= eps * (beta + 1e-7))]}

    both = prox.select("q", "v", "prox").join(weights.select("q", "v", "units"), ["q", "v"], "left").na.fill(0, ["units"])
    return _weighted(g, queries, both, "q bigint, bounds boolean, covered boolean, ratio boolean", one, "prox")


def local(g: TemporalGraph, queries: DataFrame | Iterable[int], alpha: float, *, decay: Decay, prune: bool, stop: bool, anchor: str) -> DataFrame:
    """q, v, eps, residue, expanded, visited, reason."""

    def block(a: Arrays, qs: list[int]) -> Iterator[dict]:
        for q in qs:
            members, lower, facts = a.expand(q, alpha, prune=prune, stop=stop)
            eps, found = a.shrink(members, lower, facts["residue"], q, anchor=anchor)
            yield {"q": a.ids[q], "v": a.ids[found], "eps": eps, **facts}

    return answer(g, queries, decay, "q bigint, v bigint, eps double, residue double, expanded bigint, visited bigint, reason string", block, by_slots=True)


def local_multi(g: TemporalGraph, queries: list[int], alpha: float, *, decay: Decay, prune: bool, stop: bool, anchor: str, union: bool) -> DataFrame:
    """v, eps, residue, expanded, visited, reason for a set of query vertices, in one task."""

    def block(a: Arrays, _: list[int]) -> Iterator[dict]:
        qs = [a.at(q) for q in queries]
        if None not in qs:
            own = np.array(qs)
            members, lower, facts = a.expand(own, alpha, prune=prune, stop=stop, union=union)
            if a._joins(members, own):
                eps, found = a.shrink(members, lower, facts["residue"], own, anchor=anchor)
                yield {"v": a.ids[found], "eps": eps, **facts}

    return answer(g, queries[:1], decay, "v bigint, eps double, residue double, expanded bigint, visited bigint, reason string", block, by_slots=True)


def core(g: TemporalGraph, queries: DataFrame | Iterable[int], *, temporal: bool) -> DataFrame:
    """q, v, k."""

    def block(a: Arrays, qs: list[int]) -> Iterator[dict]:
        for q in qs:
            k, found = a.best_core(np.ones(a.n, np.int64), q, a.w if temporal else None)
            yield {"q": a.ids[q], "v": a.ids[found], "k": k}

    return answer(g, queries, "reciprocal", "q bigint, v bigint, k bigint", block)


def floor_kcore(g: TemporalGraph, queries: DataFrame | Iterable[int], alpha: float, k: int) -> DataFrame:
    """q, v, floor."""

    def block(a: Arrays, qs: list[int]) -> Iterator[dict]:
        prox = a.proximity(qs, alpha)
        for c, q in enumerate(qs):
            if (found := a.floor_core(np.ascontiguousarray(prox[:, c]), q, k)) is not None:
                yield {"q": a.ids[q], "v": a.ids[found[1]], "floor": found[0]}

    return answer(g, queries, "reciprocal", "q bigint, v bigint, floor double", block)

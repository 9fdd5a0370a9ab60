"""Sequential methods on one small graph, in plain Python: what grouped tasks run, and what tests compare with."""

from __future__ import annotations

import heapq
import math
from collections import defaultdict, deque
from collections.abc import Callable, Iterable
from itertools import combinations

import numpy as np

Edge = tuple[int, int, int]
Adjacency = dict[int, set[int]]


def clean(edges: Iterable[Edge]) -> list[Edge]:
    return sorted({(min(u, v), max(u, v), t) for u, v, t in edges if u != v}, key=lambda e: (e[2], e[0], e[1]))


def adjacency(pairs: Iterable[tuple[int, int]]) -> Adjacency:
    out: Adjacency = defaultdict(set)
    for u, v in pairs:
        out[int(u)].add(int(v))
        out[int(v)].add(int(u))
    return out


def decay_function(decay: str | tuple[str, float]) -> Callable[[float], float]:
    if decay == "reciprocal":
        return lambda dt: 1 / dt
    if decay == "log":
        return lambda dt: 1 / math.log2(1 + dt)
    return lambda dt: math.exp(-decay[1] * dt)


class Walks:
    """Arc counts by vertex and time, and normalisers, of one graph."""

    def __init__(self, edges: Iterable[Edge], decay: str | tuple[str, float] = "reciprocal"):
        self.edges, self.g = clean(edges), decay_function(decay)
        self.out: dict[int, dict[int, list[int]]] = defaultdict(lambda: defaultdict(list))
        for u, v, t in self.edges:
            self.out[u][t].append(v)
            self.out[v][t].append(u)
        self.times = {v: sorted(by) for v, by in self.out.items()}
        self.norm = {(v, t): sum(len(self.out[v][s]) * self.g(s - t) for s in ts if s > t) for v, ts in self.times.items() for t in ts}

    def dense(self, q: int, alpha: float) -> dict[int, float]:
        """Proximity by a linear system over arcs: the definition itself."""
        arcs = [(a, b, t) for u, v, t in self.edges for a, b in ((u, v), (v, u))]
        at = {a: k for k, a in enumerate(arcs)}
        p = np.zeros((len(arcs), len(arcs)))
        for (a, b, t), k in at.items():
            if not self.norm[b, t]:
                p[k, k] = 1
            for s in self.times[b]:
                if s > t:
                    for w in self.out[b][s]:
                        p[k, at[b, w, s]] = self.g(s - t) / self.norm[b, t]
        start = np.array([float(a == q) for a, _, _ in arcs])
        if not start.any():
            return {}
        x = np.linalg.solve((np.eye(len(arcs)) - (1 - alpha) * p).T, alpha * start / start.sum())
        out: dict[int, float] = defaultdict(float)
        for (_, b, _), k in at.items():
            out[b] += float(x[k])
        return out

    def stream(self, q: int, alpha: float) -> dict[int, float]:
        """Proximity in one pass over the times: edges of one time don't feed each other."""
        seed = 1 / max(1, sum(len(x) for x in self.out[q].values())) if q in self.times else 0.0
        mass: dict[int, dict[int, float]] = defaultdict(dict)
        for t in sorted({t for _, _, t in self.edges}):
            here: dict[int, float] = defaultdict(float)
            for u in self._at(t):
                flow = sum((1 - alpha) * m / self.norm[u, s] * self.g(t - s) for s, m in mass[u].items() if s < t)
                flow += seed if u == q else 0.0
                if flow:
                    for w in self.out[u][t]:
                        here[w] += flow
            for w, m in here.items():
                mass[w][t] = m
        return {v: sum(m * (1.0 if not self.norm[v, t] else alpha) for t, m in by.items()) for v, by in mass.items() if by}

    def _at(self, t: int) -> list[int]:
        if not hasattr(self, "_by_time"):
            self._by_time: dict[int, list[int]] = defaultdict(list)
            for v, ts in self.times.items():
                for s in ts:
                    self._by_time[s].append(v)
        return self._by_time[t]


def connected(adj: Adjacency, members: set[int], q: int) -> set[int]:
    seen, todo = {q}, [q]
    while todo:
        for w in adj[todo.pop()] & members - seen:
            seen.add(w)
            todo.append(w)
    return seen


def smallest(adj: Adjacency, weight: dict[int, float], members: set[int]) -> float:
    return min(sum(weight.get(w, 0) for w in adj[v] & members) for v in members)


def exact_peel(adj: Adjacency, weight: dict[int, float], q: int) -> tuple[float, set[int]]:
    """The least biased degree goes first, until it is the query's; of the sets on the way the first one of the best value."""
    if q not in adj:
        return 0, set()
    alive = connected(adj, set(adj), q)
    rho = {v: sum(weight.get(w, 0) for w in adj[v] & alive) for v in alive}
    heap = [(r, v) for v, r in rho.items()]
    heapq.heapify(heap)
    order: list[int] = []
    best, cut = -1, 0
    while heap:
        r, v = heapq.heappop(heap)
        if v not in alive or r != rho[v]:
            continue
        if r > best:  # the set before this removal; a tie keeps the larger set
            best, cut = r, len(order)
        if v == q:
            break
        alive.discard(v)
        order.append(v)
        for w in adj[v] & alive:
            rho[w] -= weight.get(v, 0)
            heapq.heappush(heap, (rho[w], w))
    gone = set(order[:cut])
    return best, connected(adj, {v for v in connected(adj, set(adj), q) if v not in gone}, q)


def exact_brute(adj: Adjacency, weight: dict[int, float], q: int) -> tuple[float, set[int]]:
    """Over all subsets; the largest of the best."""
    rest, best = [v for v in adj if v != q], (-1.0, 0, {q})
    for k in range(len(rest) + 1):
        for own in combinations(rest, k):
            s = {q, *own}
            if len(s) > 1 and connected(adj, s, q) == s:
                best = max(best, (smallest(adj, weight, s), len(s), s), key=lambda x: x[:2])
    return best[0], best[2]


def expand(walks: Walks, q: int, alpha: float = 0.2, *, least: float | None = None, prune: bool = True, stop: bool = True) -> dict:
    """Pushes from the query outward, one vertex at a time, and admits what the bounds allow: members, residue, lower, beta,
    visited, reason."""
    adj = adjacency((u, v) for u, v, _ in walks.edges)
    least = 1 / len(walks.edges) if least is None else least
    residue: dict[tuple[int, int, int], float] = defaultdict(float)
    by_source: dict[int, set[tuple[int, int, int]]] = defaultdict(set)
    arcs = [(q, w, t) for t, ws in walks.out[q].items() for w in ws]
    for a in arcs:
        residue[a] = 1 / len(arcs)
        by_source[q].add(a)
    lower: dict[int, float] = defaultdict(float)
    rho: dict[int, float] = {}  # of members, from the lower bounds of their member neighbours; it never falls
    heap: list[tuple[float, int]] = []
    queue, waiting, visited, beta, reason = deque([q]), {q}, {q}, 0.0, "exhausted"
    left, near = 1.0 if arcs else 0.0, 0.0  # all residue; lower bounds of the queue

    def bank(b: int, mass: float) -> None:
        nonlocal left, near
        lower[b] += mass
        left -= mass
        near += mass if b in waiting else 0.0
        if b in rho:
            for v in adj[b]:
                if v in rho:
                    rho[v] += mass

    while queue:
        u = queue.popleft()
        waiting.discard(u)
        near -= lower[u]
        rho[u] = 0.0
        for v in adj[u]:
            if v in rho:
                rho[u] += lower[v]
                rho[v] += lower[u]
        heapq.heappush(heap, (rho[u], u))
        for a in sorted(by_source[u], key=lambda a: a[2]):
            r = residue[a]
            if r < least:
                continue
            _, b, t = a
            residue[a] = 0.0
            if not walks.norm[b, t]:
                bank(b, r)
                continue
            bank(b, alpha * r)
            for s in walks.times[b]:
                if s > t:
                    share = (1 - alpha) * r * walks.g(s - t) / walks.norm[b, t]
                    for w in walks.out[b][s]:
                        residue[b, w, s] += share
                        by_source[b].add((b, w, s))
        while heap[0][0] < rho[heap[0][1]]:  # an entry that has grown since
            v = heap[0][1]
            heapq.heapreplace(heap, (rho[v], v))
        beta = max(beta, heap[0][0])
        for v in sorted(adj[u] - visited):
            visited.add(v)
            if not prune or left + sum(lower[w] for w in adj[v]) >= beta - 1e-12:
                queue.append(v)
                waiting.add(v)
                near += lower[v]
        if stop and left + near < beta - 1e-12:
            for v in queue:
                rho[v] = 0.0
            reason = "bound"
            break
    return {"members": set(rho), "residue": max(0.0, left), "lower": dict(lower), "beta": beta, "visited": visited, "reason": reason}


def shrink(adj: Adjacency, members: set[int], lower: dict[int, float], residue: float, q: int, *, anchor: str = "max") -> tuple[float, set[int]]:
    """Halves the ratio while the query survives the removal of vertices that can't be in a community of that ratio. Where a
    bound is zero the first ratio is the one of the least positive bound: any larger one removes the same vertices."""
    rho = {v: sum(lower.get(w, 0.0) for w in adj[v] & members) for v in members}
    target = (max(rho.values()) if anchor == "max" else rho[q]) + residue
    low = min(rho.values())
    best: tuple[float, set[int]] = (target / low if low > 0 else math.inf, set(members))
    ratio, alive = target / min((x for x in rho.values() if x > 0), default=math.inf), set(members)
    while True:
        now, degree = set(alive), {v: sum(lower.get(w, 0.0) for w in adj[v] & alive) for v in alive}
        gone = [v for v in now if ratio * degree[v] < target * (1 - 1e-12)]
        queued = set(gone)
        while gone and q not in queued:
            v = gone.pop()
            now.discard(v)
            for w in adj[v] & now - queued:
                degree[w] -= lower.get(v, 0.0)
                if ratio * degree[w] < target * (1 - 1e-12):
                    queued.add(w)
                    gone.append(w)
        if q in queued or ratio < 1:
            return best[0], connected(adj, best[1], q)
        best, alive = (ratio, now), now
        ratio /= 2

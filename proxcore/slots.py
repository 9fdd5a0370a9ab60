"""Graphs in which all who share a slot of time meet: vertices and slots as arrays, edges implied.

A slot of n members has n (n - 1) / 2 temporal edges, which `compact.Arrays` would list. Here a member of a slot is one number, and
what it receives is the sum of the others' flows. The results are those of Arrays.
"""

from __future__ import annotations

import numpy as np

from proxcore.compact import Arrays, Decay, _runs, _weight

#: Neighbours that are listed in advance; beyond, each vertex's are found anew.
MOST_LISTED = 40_000_000


def _others(x: np.ndarray) -> np.ndarray:
    """For each row the sum of all other rows; nothing is subtracted."""
    before, after = np.zeros_like(x), np.zeros_like(x)
    np.cumsum(x[:-1], axis=0, out=before[1:])
    np.cumsum(x[:0:-1], axis=0, out=after[-2::-1])
    return before + after


class Slots(Arrays):
    """Vertices count from 0 in order of their ids; states (v, t) are in order of time, one for each member of a slot."""

    def __init__(self, v: np.ndarray, t: np.ndarray, decay: Decay = "reciprocal"):
        times, time_of, sizes = np.unique(t, return_inverse=True, return_counts=True)
        v, t = v[sizes[time_of] > 1], t[sizes[time_of] > 1]  # who is alone meets nobody
        self.ids, vertex = np.unique(v, return_inverse=True)
        times, slot_of, self.size = np.unique(t, return_inverse=True, return_counts=True)
        order = np.lexsort((vertex, slot_of))
        self.n, self.state_v, self.slot_of = len(self.ids), vertex[order], slot_of[order]
        self.state_at = np.r_[0, np.cumsum(self.size)]
        self.n_out = self.size[self.slot_of] - 1
        self.m = int((self.size * (self.size - 1)).sum() // 2)
        self.by_vertex = np.argsort(self.state_v, kind="stable")
        self.held = np.bincount(self.state_v, minlength=self.n)
        self.first_state = np.cumsum(self.held) - self.held
        place = np.arange(len(self.state_v))
        later = np.repeat(self.first_state + self.held, self.held) - place - 1
        by_vertex = self.by_vertex.astype(np.int32)
        early, late = by_vertex[np.repeat(place, later)], by_vertex[_runs(place + 1, later)]
        g = _weight((times[self.slot_of[late]] - times[self.slot_of[early]]).astype(np.float64), decay)
        norm = np.bincount(early, self.n_out[late] * g, len(place))
        by_late = np.argsort(late, kind="stable")
        self.early, self.late, self.share = early[by_late], late[by_late], (g / norm[early])[by_late]
        self.dangling = np.empty(len(place), bool)
        self.dangling[self.by_vertex] = later == 0
        self.pair_at = np.searchsorted(self.late, self.state_at)
        self.out = np.bincount(self.state_v, self.n_out, self.n)
        self._stamp = np.zeros(self.n, np.int64)
        self._listed: tuple[np.ndarray, np.ndarray] | None = None
        most = np.bincount(self.state_v, self.n_out, self.n).sum()
        if self.n and most <= MOST_LISTED:
            near = [self._found(k) for k in range(self.n)]
            self._listed = np.concatenate(near), np.r_[0, np.cumsum([len(x) for x in near])]

    def _members(self, slots: np.ndarray) -> np.ndarray:
        return self.state_v[_runs(self.state_at[slots], self.size[slots])]

    def _found(self, v: int) -> np.ndarray:
        first = self.first_state[v]
        x = self._members(self.slot_of[self.by_vertex[first : first + self.held[v]]])
        k = np.arange(len(x))
        self._stamp[x] = k
        return x[(self._stamp[x] == k) & (x != v)].astype(np.int32)

    def neighbours(self, v: int) -> np.ndarray:
        """Each once."""
        if self._listed is None:
            return self._found(v)
        y, at = self._listed
        return y[at[v] : at[v + 1]]

    def degrees(self, values: np.ndarray, of: np.ndarray | None = None) -> np.ndarray:
        """The sum over each vertex's neighbours; 0 for those not asked for."""
        out = np.zeros(self.n, values.dtype)
        for v in range(self.n) if of is None else of:
            out[v] = values[self.neighbours(v)].sum()
        return out

    def proximity(self, qs: list[int], alpha: float) -> np.ndarray:
        mass = np.zeros((len(self.state_v), len(qs)))
        start = np.zeros((self.n, len(qs)))
        start[qs, np.arange(len(qs))] = 1 / self.out[qs]
        for k in range(len(self.size)):
            low, high = self.state_at[k], self.state_at[k + 1]
            flow = start[self.state_v[low:high]]
            p, r = self.pair_at[k], self.pair_at[k + 1]
            if p < r:
                late = self.late[p:r]
                heads = np.flatnonzero(np.r_[True, late[1:] != late[:-1]])
                flow[late[heads] - low] += (1 - alpha) * np.add.reduceat(self.share[p:r, None] * mass[self.early[p:r]], heads, axis=0)
            mass[low:high] = _others(flow)
        mass[~self.dangling] *= alpha
        return np.add.reduceat(mass[self.by_vertex], self.first_state, axis=0)

    def component(self, alive: np.ndarray, q: int) -> np.ndarray:
        seen, used = np.zeros(self.n, bool), np.zeros(len(self.size), bool)
        seen[q] = True
        frontier = np.array([q])
        while len(frontier):
            slots = np.unique(self.slot_of[self.by_vertex[_runs(self.first_state[frontier], self.held[frontier])]])
            slots = slots[~used[slots]]
            used[slots] = True
            near = self._members(slots)
            frontier = np.unique(near[alive[near] & ~seen[near]])
            seen[frontier] = True
        return np.flatnonzero(seen)

    def core_numbers(self, units: np.ndarray, until: int | None = None) -> np.ndarray:
        """The largest threshold whose core holds each vertex; with until only up to that vertex's own, which those above get too."""
        gone_from = np.iinfo(np.int64).max // 2
        rho, core, level = self.degrees(units), np.zeros(self.n, np.int64), 0
        alive, left = np.ones(self.n, bool), self.n
        while left:
            level = max(level, int(rho.min()))
            gone = np.flatnonzero(alive & (rho <= level))
            if until is not None and rho[until] <= level:
                break
            core[gone], alive[gone] = level, False
            left -= len(gone)
            for v in gone[units[gone] > 0]:
                rho[self.neighbours(v)] -= units[v]
            rho[~alive] = gone_from
        core[alive] = level
        return core

    def best_core(self, units: np.ndarray, q: int, w: np.ndarray | None = None) -> tuple[int, np.ndarray]:
        core = self.core_numbers(units, q)
        return int(core[q]), self.component(core >= core[q], q)

    def expand(self, q: int | np.ndarray, alpha: float, *, least: float | None = None, prune: bool = True, stop: bool = True, union: bool = False) -> tuple[np.ndarray, np.ndarray, dict]:
        """As in Arrays: all arcs that leave a vertex in a slot hold the same residue, so it is kept once for each state."""
        least = 1 / self.m if least is None else least
        qs = np.atleast_1d(q)
        start = np.zeros(self.n)
        start[qs] = 1.0 / self.out[qs].sum() if union else 1.0 / (self.out[qs] * len(qs))
        residue = start[self.state_v]
        lower, members, visited, active = np.zeros(self.n), np.zeros(self.n, bool), np.zeros(self.n, bool), np.zeros(self.n, bool)
        visited[qs] = True
        queue, beta, left, reason, whole = qs, 0.0, 1.0, "exhausted", len(qs) == 1
        while len(queue):
            members[queue] = True
            active[:] = False
            active[queue] = True
            hot = (residue >= least) & active[self.state_v]
            pushed = np.where(hot, residue, 0.0)
            mass = np.zeros(len(pushed))
            for k in np.unique(self.slot_of[hot]):
                s = slice(self.state_at[k], self.state_at[k + 1])
                mass[s] = _others(pushed[s])
            residue[hot] = 0.0
            lower += np.bincount(self.state_v, np.where(self.dangling, mass, alpha * mass), self.n)
            residue += np.bincount(self.late, (1 - alpha) * self.share * mass[self.early], len(mass))
            left = float((residue * self.n_out).sum())
            whole = whole or self._joins(members, qs)
            beta = max(beta, float(self.degrees(lower * members, np.flatnonzero(members))[members].min())) if whole else beta
            near = self._members(np.unique(self.slot_of[self.by_vertex[_runs(self.first_state[queue], self.held[queue])]]))
            fresh = np.unique(near[~visited[near]])
            visited[fresh] = True
            queue = fresh[left + self.degrees(lower, fresh)[fresh] >= beta - 1e-12] if prune else fresh
            if stop and len(queue) and left + lower[queue].sum() < beta - 1e-12:
                members[queue] = True
                reason = "bound"
                break
        return members, lower, {"residue": left, "expanded": int(members.sum()), "visited": int(visited.sum()), "reason": reason}

    def _sums(self, values: np.ndarray, of: np.ndarray) -> np.ndarray:
        return self.degrees(values, np.flatnonzero(of))

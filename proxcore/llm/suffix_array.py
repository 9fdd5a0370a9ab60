"""Suffix arrays by linear grouping.

Phase one gathers suffixes that share their longest Lyndon prefix. Groups start as those of equal first symbols and are
taken in descending order. For each suffix of the group at hand its previous-smaller pointer leads to the nearest suffix
before it that is in a lower group; how often a suffix is pointed to says how many copies of the group's prefix its own
prefix grows by, so it moves to a new group right above its old one, above those that grow by less. Phase two needs no
renaming: suffixes are emitted in ascending order, and each one that is emitted puts those whose Lyndon prefix ends
before it, a chain of previous-smaller pointers, at the next free places of their groups.
"""

from __future__ import annotations

from collections.abc import Sequence


def suffix_array(text: Sequence[int]) -> list[int]:
    """Starts of the suffixes of a text of small non-negative numbers, in ascending order."""
    n = len(text)
    if not n:
        return []
    by_symbol: dict[int, list[int]] = {}
    for i, c in enumerate(text):
        by_symbol.setdefault(c, []).append(i)
    symbols = sorted(by_symbol)
    members = [by_symbol[c] for c in symbols]  # may still list suffixes that have moved on
    below = list(range(-1, len(symbols) - 1))  # the next lower group
    numbers = {c: g for g, c in enumerate(symbols)}
    group = [numbers[c] for c in text]
    done = bytearray(n)
    previous = [-1] * n
    ends: list[int] = []  # of groups, as taken
    place = [0] * n
    high, now = n, len(symbols) - 1
    above = [*range(1, len(symbols)), -1]
    while now >= 0:
        own = [i for i in members[now] if group[i] == now]
        members[now] = []
        high -= len(own)
        for i in own:
            done[i] = 1
            place[i] = high
        counts: dict[int, int] = {}
        for i in own:
            p = i - 1
            while p >= 0 and done[p]:
                p = previous[p]
            previous[i] = p
            if p >= 0:
                counts[p] = counts.get(p, 0) + 1
        if counts:
            if len(counts) == 1:
                (p,) = counts
                moves = [(group[p], 1, [p])]
            else:
                gathered: dict[tuple[int, int], list[int]] = {}
                for p, times in counts.items():
                    gathered.setdefault((times, group[p]), []).append(p)
                moves = [(g, times, gathered[times, g]) for times, g in sorted(gathered, reverse=True)]
            for g, _, own in moves:
                fresh = len(members)
                members.append(own)
                for p in own:
                    group[p] = fresh
                top = above[g]
                below.append(g)
                above.append(top)
                above[g] = fresh
                below[top] = fresh
        ends.append(high)
        now = below[now]
    out = [-1] * n
    free = place  # the next free place of a group is kept at the group's number
    starts: dict[int, int] = {}
    for i in range(n):
        starts.setdefault(group[i], free[i])
    p = n - 1  # the end of the text is the first that is emitted
    while p >= 0:
        g = group[p]
        out[starts[g]] = p
        starts[g] += 1
        p = previous[p]
    for k in range(n):
        stop = previous[out[k]]
        p = out[k] - 1
        while p > stop:
            g = group[p]
            out[starts[g]] = p
            starts[g] += 1
            p = previous[p]
    return out

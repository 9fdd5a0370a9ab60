"""Elias-Fano sequences and the n-gram trie made of them, as flat buffers that may be memory-mapped.

A sequence of n values below u keeps the low bits of each value packed, and its high bits in unary; a directory of
zeros before each word of the unary part leads to any high part. All look-ups take whole arrays.

The trie has a level of contexts (monotone by themselves) and a level of successors. A successor is kept relative to its
context: within a context's range the word numbers ascend, and the level is made monotone by adding to each range what the
ranges before it have reached, so a successor is found by looking for that sum plus its word within the range. Monotone
pointers give the ranges. Each successor has a quantised log probability.
"""

from __future__ import annotations

import numpy as np

_ONE = np.uint64(1)
#: Place of the k-th one in each byte value, 8 if it has fewer.
_SELECT = np.full((256, 8), 8, np.uint8)
for _b in range(256):
    for _k, _at in enumerate([i for i in range(8) if _b >> i & 1]):
        _SELECT[_b, _k] = _at


def pack(values: np.ndarray) -> bytes:
    """Of ascending values, repeats allowed."""
    v = np.asarray(values, np.uint64)
    n = len(v)
    top = int(v[-1]) + 1 if n else 1
    bits = max(0, (top // max(n, 1)).bit_length() - 1)
    low, high = v & np.uint64((1 << bits) - 1), (v >> np.uint64(bits)).astype(np.int64)
    ones = high + np.arange(n)
    size = (int(ones[-1]) + 1 if n else 0) // 64 + 1
    unary = np.zeros(size * 64, np.uint8)
    unary[ones] = 1
    words = np.packbits(unary, bitorder="little").view(np.uint64)
    zeros = np.concatenate([[0], np.cumsum(64 - np.bitwise_count(words).astype(np.int64))]).astype(np.int64)
    packed = np.zeros(n * bits // 64 + 2, np.uint64)
    at = np.arange(n, dtype=np.uint64) * np.uint64(bits)
    word, shift = (at >> np.uint64(6)).astype(np.int64), at & np.uint64(63)
    np.bitwise_or.at(packed, word, low << shift)
    over = shift + np.uint64(bits) > 64
    np.bitwise_or.at(packed, word[over] + 1, low[over] >> (np.uint64(64) - shift[over]))
    head = np.array([n, bits, size, len(packed)], np.int64)
    return b"".join(x.tobytes() for x in (head, words, zeros, packed))


class Sequence:
    def __init__(self, buffer: memoryview | np.ndarray, offset: int = 0):
        head = np.frombuffer(buffer, np.int64, 4, offset)
        self.n, self.bits, size, low = map(int, head)
        offset += 32
        self.words = np.frombuffer(buffer, np.uint64, size, offset)
        self.bytes = self.words.view(np.uint8)
        self.zeros = np.frombuffer(buffer, np.int64, size + 1, offset := offset + size * 8)
        self.low = np.frombuffer(buffer, np.uint64, low, offset := offset + (size + 1) * 8)
        self.end = offset + low * 8

    def _select(self, k: np.ndarray, of_ones: bool) -> np.ndarray:
        """Places of the k-th one or zero of the unary part; for zeros beyond the last, those that would follow."""
        before = np.arange(len(self.zeros)) * 64 - self.zeros if of_ones else self.zeros
        word = np.minimum(np.searchsorted(before, k, "right") - 1, len(self.words) - 1)
        left = k - before[word]
        bits = self.words[word] if of_ones else ~self.words[word]
        place = word * 64
        todo = np.ones(len(k), bool)
        for _ in range(8):
            byte = (bits & np.uint64(255)).astype(np.int64)
            n = np.bitwise_count(byte.astype(np.uint8)).astype(np.int64)
            here = todo & (left < n)
            place[here] += _SELECT[byte[here], left[here]]
            todo &= ~here
            left[todo] -= n[todo]
            place[todo] += 8
            bits = bits >> np.uint64(8)
        place[todo] += left[todo]
        return place

    def _low(self, at: np.ndarray) -> np.ndarray:
        if not self.bits:
            return np.zeros(len(at), np.uint64)
        bit = at.astype(np.uint64) * np.uint64(self.bits)
        word, shift = (bit >> np.uint64(6)).astype(np.int64), bit & np.uint64(63)
        out = self.low[word] >> shift
        over = shift > 0
        out[over] |= self.low[word[over] + 1] << (np.uint64(64) - shift[over])
        return out & np.uint64((1 << self.bits) - 1)

    def get(self, at: np.ndarray) -> np.ndarray:
        at = np.asarray(at, np.int64)
        high = (self._select(at, True) - at).astype(np.uint64)
        return high << np.uint64(self.bits) | self._low(at)

    def successor(self, values: np.ndarray) -> np.ndarray:
        """Places of the first elements that are at least the given values; n where there is none."""
        values = np.asarray(values, np.uint64)
        high = (values >> np.uint64(self.bits)).astype(np.int64)
        last = int(self.zeros[-1])
        beyond = high > last
        high = np.minimum(high, last)
        # elements of lower high parts come before the (high - 1)-th zero
        low = np.where(high > 0, self._select(np.maximum(high - 1, 0), False) - (high - 1), 0)
        low = np.clip(np.where(beyond, self.n, low), 0, self.n)
        top = np.clip(np.where(beyond, self.n, self._select(high, False) - high), 0, self.n)
        want = values & np.uint64((1 << self.bits) - 1)
        while (open_ := np.flatnonzero(low < top)).size:
            mid = (low[open_] + top[open_]) // 2
            less = self._low(mid) < want[open_]
            low[open_[less]] = mid[less] + 1
            top[open_[~less]] = mid[~less]
        return low


#: A step of the quantised log10 probabilities, kept in 16 bits.
STEP = 1 / 4096


def build(context: np.ndarray, word: np.ndarray, log_p: np.ndarray) -> bytes:
    """A trie of distinct pairs, sorted by context, then word (both below 2^40)."""
    heads, first = np.unique(context, return_index=True)
    bounds = np.append(first, len(context)).astype(np.int64)
    # what a range adds to the next: its last word plus one
    lift = np.concatenate([[0], np.cumsum(word[bounds[1:] - 1].astype(np.uint64) + _ONE)]).astype(np.uint64) if len(word) else np.zeros(1, np.uint64)
    level = word.astype(np.uint64) + np.repeat(lift[:-1], np.diff(bounds))
    codes = np.minimum(np.rint(-log_p / STEP), 65535).astype(np.uint16)
    parts = [pack(heads), pack(bounds), pack(lift), pack(level), np.array([len(codes)], np.int64).tobytes(), codes.tobytes()]
    return b"".join(parts)


class Trie:
    def __init__(self, buffer: memoryview | np.ndarray):
        self.heads = Sequence(buffer)
        self.bounds = Sequence(buffer, self.heads.end)
        self.lift = Sequence(buffer, self.bounds.end)
        self.level = Sequence(buffer, self.lift.end)
        n = int(np.frombuffer(buffer, np.int64, 1, self.level.end)[0])
        self.codes = np.frombuffer(buffer, np.uint16, n, self.level.end + 8)

    def log_p(self, context: np.ndarray, word: np.ndarray) -> np.ndarray:
        """Of pairs; NaN for those the trie doesn't have."""
        out = np.full(len(context), np.nan)
        if not self.heads.n or not len(context):
            return out
        context, word = np.asarray(context, np.uint64), np.asarray(word, np.uint64)
        node = np.minimum(self.heads.successor(context), self.heads.n - 1)
        has = np.flatnonzero(self.heads.get(node) == context)
        node = node[has]
        base, limit = self.lift.get(node), self.lift.get(node + 1)
        want = base + word[has]
        inside = want < limit  # beyond the range's last word nothing is found, and the next range begins
        has, want = has[inside], want[inside]
        at = np.minimum(self.level.successor(want), self.level.n - 1)
        found = self.level.get(at) == want
        out[has[found]] = -self.codes[at[found]].astype(np.float64) * STEP
        return out

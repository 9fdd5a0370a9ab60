"""Byte-level BPE by a segment tree over byte positions: a leaf holds the rank of the pair that starts there, a node
the least (rank, position) below it, so the root is always the leftmost pair of the lowest rank. A merge changes the
leaves of the pair, of its dead right part and of the live left neighbour, each in a logarithmic number of steps.

Short pieces are merged many at a time: the trees of a batch are rows of one array, and a step does one merge in each
row. A long piece has a tree of its own. Both give what the rank file's reference encoder gives: a piece that is itself
a token is that token, all others are merged by rank. Special tokens are ordinary text.

Defined results: a null or empty text has no tokens and decodes to nothing; rows and extra columns pass through; the
time for a piece of n bytes is O(n log n), so that a text of one very long run is no special case.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterable

import numpy as np
import public_tokenizers
import regex
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

from proxcore.llm.common import with_struct

FILE = "byte_bpe_50k.tiktoken"
#: Bytes of a rank file that may be broadcast, pieces that a worker remembers, bytes of pieces merged in a batch.
MOST_RANK_BYTES, REMEMBERED, SHORT = 64_000_000, 120_000, 32

ENCODED = T.StructType([T.StructField("n_tokens", T.LongType()), T.StructField("ids", T.ArrayType(T.IntegerType()))])
TRIP = T.StructType([T.StructField("n_tokens", T.LongType()), T.StructField("ids_sha256", T.StringType()), T.StructField("decoded_sha256", T.StringType())])
FULL = T.StructType([*TRIP.fields, T.StructField("ids", T.ArrayType(T.IntegerType()))])


class Codec:
    def __init__(self, ranks: bytes, pattern: str):
        self.rank = {base64.b64decode(a): int(b) for a, b in (line.split() for line in ranks.splitlines() if line)}
        self.token = {v: k for k, v in self.rank.items()}
        self.split = regex.compile(pattern).findall
        self.known: dict[str, tuple[int, ...]] = {}
        self.none = max(self.rank.values()) + 1
        # the pairs that merge, by the numbers of their parts
        pairs = {}
        for whole, r in self.rank.items():
            for k in range(1, len(whole)):
                if (a := self.rank.get(whole[:k])) is not None and (b := self.rank.get(whole[k:])) is not None:
                    pairs[a << 32 | b] = r
        self.pair = pairs
        self.keys = np.array(sorted(pairs), np.int64)
        self.made = np.array([pairs[int(k)] for k in self.keys], np.int64)
        self.byte = np.array([self.rank.get(bytes([k]), -1) for k in range(256)], np.int64)
        # an open-addressed table of the same pairs, for whole arrays at a time
        self.bits = max(4, int(len(self.keys) * 4).bit_length())
        self.slots = np.full(1 << self.bits, -1, np.int64)
        self.values = np.full(1 << self.bits, self.none, np.int64)
        todo, probe = np.arange(len(self.keys)), self._slot(self.keys)
        while len(todo):
            free = self.slots[probe[todo]] < 0
            at, first = np.unique(probe[todo][free], return_index=True)
            put = todo[free][first]
            self.slots[at], self.values[at] = self.keys[put], self.made[put]
            todo = np.setdiff1d(todo, put)
            probe[todo] = (probe[todo] + 1) & ((1 << self.bits) - 1)

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def _ranks(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Of pairs of tokens; none where they don't merge."""
        key = left << 32 | right
        at = self._slot(key)
        seen = self.slots[at]
        out = np.where(seen == key, self.values[at], self.none)
        todo = np.flatnonzero((seen != key) & (seen >= 0))
        while len(todo):
            at[todo] = (at[todo] + 1) & (len(self.slots) - 1)
            seen = self.slots[at[todo]]
            right_one = seen == key[todo]
            out[todo[right_one]] = self.values[at[todo[right_one]]]
            todo = todo[~right_one & (seen >= 0)]
        return out

    def merge_long(self, piece: bytes) -> list[int]:
        """One piece with a tree of its own."""
        n, pair, none = len(piece), self.pair, self.none
        ids = [self.rank[piece[k : k + 1]] for k in range(n)]
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        size = 1 << max(1, (n - 1).bit_length())
        shift = size.bit_length()
        worst = none << shift
        tree = [worst] * (2 * size)
        for k in range(n - 1):
            tree[size + k] = pair.get(ids[k] << 32 | ids[k + 1], none) << shift | k
        for k in range(size - 1, 0, -1):
            tree[k] = min(tree[2 * k], tree[2 * k + 1])

        def put(k: int, value: int) -> None:
            k += size
            tree[k] = value
            while k > 1:
                k >>= 1
                least = min(tree[2 * k], tree[2 * k + 1])
                if tree[k] == least:
                    break
                tree[k] = least

        while tree[1] < worst:
            at, made = tree[1] & (size - 1 | size), tree[1] >> shift
            gone = after[at]
            ids[at], ids[gone] = made, -1
            after[at] = far = after[gone]
            put(gone, worst)
            if far < n:
                before[far] = at
                put(at, pair.get(made << 32 | ids[far], none) << shift | at)
            else:
                put(at, worst)
            if (left := before[at]) >= 0:
                put(left, pair.get(ids[left] << 32 | made, none) << shift | left)
        return [x for x in ids if x >= 0]

    def merge_short(self, pieces: list[bytes], width: int) -> list[tuple[int, ...]]:
        """Pieces of at most `width` bytes, a power of two: their trees are the rows of one array, level by level."""
        rows, none = len(pieces), self.none
        lens = np.fromiter(map(len, pieces), np.int64, rows)
        raw = np.frombuffer(b"".join(x.ljust(width, b"\0") for x in pieces), np.uint8).reshape(rows, width)
        ids = self.byte[raw]
        here = np.arange(width)
        ids[here >= lens[:, None]] = -1
        after = np.broadcast_to(here + 1, (rows, width)).copy()
        before = np.broadcast_to(here - 1, (rows, width)).copy()
        shift = width.bit_length()
        worst = none << shift
        tree = np.full((rows, 2 * width), worst, np.int64)
        r, c = np.nonzero(here[: width - 1] < lens[:, None] - 1)
        tree[r, width + c] = np.where((rank := self._ranks(ids[r, c], ids[r, c + 1])) < none, rank << shift | c, worst)
        low = width
        while low > 1:
            tree[:, low // 2 : low] = np.minimum(tree[:, low : 2 * low : 2], tree[:, low + 1 : 2 * low : 2])
            low //= 2

        def put(row: np.ndarray, col: np.ndarray, value: np.ndarray | int) -> None:
            k = col + width
            tree[row, k] = value
            while k[0] > 1:  # all rows have trees of one height
                k >>= 1
                tree[row, k] = np.minimum(tree[row, 2 * k], tree[row, 2 * k + 1])

        def renew(row: np.ndarray, col: np.ndarray, left: np.ndarray, right: np.ndarray) -> None:
            rank = self._ranks(left, right)
            put(row, col, np.where(rank < none, rank << shift | col, worst))

        live = np.flatnonzero(tree[:, 1] < worst)
        while len(live):
            top = tree[live, 1]
            at, made = top & ((1 << shift) - 1), top >> shift
            gone = after[live, at]
            ids[live, at] = made
            ids[live, gone] = -1
            far = after[live, gone]
            after[live, at] = far
            put(live, gone, worst)
            there = far < lens[live]
            if there.any():
                x = live[there]
                before[x, far[there]] = at[there]
                renew(x, at[there], made[there], ids[x, far[there]])
            if not there.all():
                put(live[~there], at[~there], worst)
            left = before[live, at]
            there = left >= 0
            if there.any():
                x = live[there]
                renew(x, left[there], ids[x, left[there]], made[there])
            live = live[tree[live, 1] < worst]
        flat = ids[ids >= 0].tolist()
        ends = np.cumsum((ids >= 0).sum(1)).tolist()
        return [tuple(flat[a:b]) for a, b in zip([0, *ends[:-1]], ends, strict=True)]

    def learn(self, pieces: Iterable[str]) -> dict[str, tuple[int, ...]]:
        """Encodes pieces that aren't known yet. Only short ones are remembered; all others are returned."""
        long: dict[str, tuple[int, ...]] = {}
        groups: dict[int, list[tuple[str, bytes]]] = {}
        for piece in pieces:
            raw = piece.encode("utf-8", "surrogatepass")
            if (whole := self.rank.get(raw)) is not None:
                (self.known if len(raw) <= SHORT else long)[piece] = (whole,)
            elif len(raw) <= SHORT:
                groups.setdefault(max(4, 1 << (len(raw) - 1).bit_length()), []).append((piece, raw))
            else:
                long[piece] = tuple(self.merge_long(raw))
        for width, own in groups.items():
            for low in range(0, len(own), 4096):
                part = own[low : low + 4096]
                self.known.update(zip([x for x, _ in part], self.merge_short([x for _, x in part], width), strict=True))
        return long

    def encode_all(self, texts: Iterable[str | None]) -> list[np.ndarray]:
        if len(self.known) > REMEMBERED:
            self.known.clear()
        split = [self.split(x) if x else [] for x in texts]
        long = self.learn({p for pieces in split for p in pieces if p not in self.known})
        get, out = (lambda p, known=self.known: known[p] if p in known else long[p]) if long else self.known.__getitem__, []
        for pieces in split:
            ids: list[int] = []
            for x in map(get, pieces):
                ids += x
            out.append(np.array(ids, np.uint32))
        return out

    def decode(self, ids: Iterable[int]) -> bytes:
        return b"".join(map(self.token.__getitem__, ids))


_codecs: dict[str, Codec] = {}


def codec(sent: Broadcast) -> Codec:
    mark, ranks, pattern = sent.value
    if mark not in _codecs:
        _codecs.clear()
        _codecs[mark] = Codec(ranks, pattern)
    return _codecs[mark]


def load(spark: SparkSession, path: str | None = None, pattern: str | None = None) -> Broadcast:
    """The rank file is read on the driver and broadcast if it is within MOST_RANK_BYTES."""
    with open(path or public_tokenizers.path(FILE), "rb") as f:
        ranks = f.read(MOST_RANK_BYTES + 1)
    if len(ranks) > MOST_RANK_BYTES:
        raise ValueError(f"a rank file of over {MOST_RANK_BYTES} bytes isn't broadcast")
    pattern = pattern or public_tokenizers.PATTERN
    return spark.sparkContext.broadcast((hashlib.sha256(ranks + pattern.encode()).hexdigest(), ranks, pattern))


def encode(docs: DataFrame, *, text: str = "text", path: str | None = None, pattern: str | None = None, out: str = "encoded") -> DataFrame:
    """docs with the struct column `out`: n_tokens, ids."""
    sent = load(docs.sparkSession, path, pattern)
    return with_struct(docs, text, out, ENCODED, lambda texts: [{"n_tokens": len(x), "ids": x} for x in codec(sent).encode_all(texts)])


def decode(docs: DataFrame, *, ids: str = "ids", path: str | None = None, pattern: str | None = None, out: str = "decoded") -> DataFrame:
    """docs with the struct column `out`: raw, the bytes that the ids stand for; null ids have none."""
    sent = load(docs.sparkSession, path, pattern)
    kind = T.StructType([T.StructField("raw", T.BinaryType())])
    return with_struct(docs, ids, out, kind, lambda rows: [{"raw": codec(sent).decode(x or ())} for x in rows])


def round_trip(docs: DataFrame, *, text: str = "text", path: str | None = None, pattern: str | None = None, out: str = "trip", with_ids: bool = False) -> DataFrame:
    """docs with the struct column `out`: encodes each text, decodes the ids again, and gives digests of both."""
    sent = load(docs.sparkSession, path, pattern)

    def make(texts: Iterable[str | None]) -> list[dict]:
        own = codec(sent)
        return [{"n_tokens": len(x), "ids_sha256": hashlib.sha256(x.astype("<u4").tobytes()).hexdigest(), "decoded_sha256": hashlib.sha256(own.decode(x.tolist())).hexdigest()} | ({"ids": x} if with_ids else {}) for x in own.encode_all(texts)]

    return with_struct(docs, text, out, FULL if with_ids else TRIP, make)

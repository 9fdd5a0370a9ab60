"""Language-model scoring: a bigram model in Elias-Fano tries, trained on the corpus it scores, without the held-out part.

    p(w | b) = (c(b w) + prior * p(w)) / (c(b) + prior),   p(w) = (c(w) + 1) / (N + V + 1)

A text is lower-cased (A-Z), split at ASCII white space and closed by an end token, which is also the context of a first
word. The probabilities of seen pairs are quantised to 16 bits; V + 1 counts one more word, for all that training lacks.

Nothing grows with the corpus on one machine. Texts are packed into blocks. (1) A block sends its distinct words, by
hash, to word shards, which count them over all blocks and give back numbers and counts. (2) With these a block sends its
distinct pairs to pair shards: counts, and the places of their documents. A shard sums the counts of all blocks, builds
its trie, maps it into memory, and looks up every pair it was sent. (3) Each block sums what comes back by document.
Shards go by the hash of a whole word or pair, and a frequent one is one entry of a block, so none is hot.

With order 3 or more, contexts of several words are smoothed by the next shorter ones,

    p(w | a b) = (c(a b w) + prior * p(w | b)) / (c(a b) + prior)

and the words at the start of a text have as long a context as there is: the end token and what follows it. (1) A block sends its distinct grams of all
orders at once, by 64-bit keys made of the words' hashes, to gram shards. (2) A shard sums their counts, puts them into a trie for each order, looks up what
it was sent and gives back counts alone. (3) Each block scores its documents. Keys are sent once and no place of a document is, which keeps this exchange
small enough for three words.

Defined results: a null or empty text is one end token; a null id is trained on; repeated rows count and are scored each
time; without any training token all words are unknown; extra columns are dropped; an empty table gives no rows.
"""

from __future__ import annotations

import mmap
import tempfile
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxcore.llm import elias_fano
from proxcore.llm.common import keep, partitions

#: Bytes of text in a block at most, but for a longer last text; the strength of the unigram prior.
BLOCK_BYTES, PRIOR = 12_000_000, 400.0
_MIX = np.uint64(0x9E3779B97F4A7C15)


def dump(*arrays: np.ndarray) -> bytes:
    """Arrays as compressed bytes, low and high bytes apart."""
    out = []
    for x in arrays:
        raw = np.ascontiguousarray(x)
        planes = raw.view(np.uint8).reshape(len(raw), raw.itemsize).T.tobytes() if len(raw) else b""
        out.append(raw.dtype.str.encode().ljust(4) + len(raw).to_bytes(8, "little") + planes)
    return zstandard.ZstdCompressor(level=1).compress(b"".join(out))


def load(data: bytes) -> list[np.ndarray]:
    raw, at, out = zstandard.ZstdDecompressor().decompress(data), 0, []
    while at < len(raw):
        kind, n = np.dtype(raw[at : at + 4].decode().strip()), int.from_bytes(raw[at + 4 : at + 12], "little")
        at += 12
        size = n * kind.itemsize
        out.append(np.frombuffer(raw, np.uint8, size, at).reshape(kind.itemsize, n).T.copy().reshape(-1).view(kind) if n else np.empty(0, kind))
        at += size
    return out


def tight(x: np.ndarray) -> np.ndarray:
    """In the least unsigned type that holds it."""
    top = int(x.max()) if len(x) else 0
    return x.astype(np.uint8 if top < 1 << 8 else np.uint16 if top < 1 << 16 else np.uint32 if top < 1 << 32 else np.uint64)


def _runs(sorted_values: np.ndarray) -> np.ndarray:
    """Where each run of equal values starts."""
    return np.flatnonzero(np.concatenate([[True], sorted_values[1:] != sorted_values[:-1]])) if len(sorted_values) else np.empty(0, np.int64)


def _pack_blocks(n_shards: int, block_bytes: int):  # noqa: ANN202
    def pack(block: int, docs: list[tuple[int | None, bool, np.ndarray]]) -> Iterator[tuple]:
        lens = np.array([len(t) for _, _, t in docs], np.int64)
        held = np.array([h for _, h, _ in docs], bool)
        tokens = np.concatenate([t for _, _, t in docs])
        words, inverse = np.unique(tokens, return_inverse=True)
        trained = np.bincount(inverse[np.repeat(~held, lens)], minlength=len(words))
        shard = (words % np.uint64(max(1, n_shards))).astype(np.int64)
        order = np.argsort(shard, kind="stable")  # by shard, then hash
        place = np.empty(len(words), np.int64)
        place[order] = np.arange(len(words))
        ids = np.array([0 if d is None else d for d, _, _ in docs], np.int64)
        own_words = None if n_shards else dump(np.diff(words, prepend=np.uint64(0)))  # without shards they stay with the block
        yield block, -1, dump(ids, np.array([d is None for d, _, _ in docs], np.uint8), held.astype(np.uint8), tight(lens), tight(place[inverse])), own_words
        if not n_shards:
            return
        starts = np.searchsorted(shard[order], np.arange(n_shards + 1))
        for s in range(n_shards):
            own = order[starts[s] : starts[s + 1]]
            if len(own):
                yield block, s, None, dump(np.diff(words[own], prepend=np.uint64(0)), tight(trained[own]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number, size, docs = TaskContext.get().partitionId() << 32, 0, []
        schema = pa.schema([("block", pa.int64()), ("shard", pa.int32()), ("tokens", pa.binary()), ("words", pa.binary())])

        def flush() -> Iterator[pa.RecordBatch]:
            for row in pack(number, docs):
                yield pa.RecordBatch.from_arrays([pa.array([x], t) for x, t in zip(row, schema.types, strict=True)], schema=schema)

        for batch in batches:
            for doc_id, held, text in zip(batch.column("doc_id").to_pylist(), batch.column("held_out").to_pylist(), batch.column("text"), strict=True):
                raw = (text.as_py() or "").encode("utf-8", "surrogatepass").lower()
                words = raw.split()
                words.append(b"\n")  # the end; no word has white space
                docs.append((doc_id, held, np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))))
                size += len(raw)
                if size >= block_bytes:
                    yield from flush()
                    number, size, docs = number + 1, 0, []
        if docs:
            yield from flush()

    return run


def _count_words(n_shards: int):  # noqa: ANN202
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        shard = int(pdf["shard"].iloc[0])
        parts = [load(x) for x in pdf["words"]]
        words = [np.cumsum(w, dtype=np.uint64) for w, _ in parts]
        all_words, inverse = np.unique(np.concatenate(words), return_inverse=True)
        counts = np.bincount(inverse, np.concatenate([c for _, c in parts])).astype(np.int64)
        ends = np.cumsum([len(w) for w in words])
        rows = [(int(b), shard, dump(tight(at * n_shards + shard), tight(counts[at])), 0, 0) for b, at in zip(pdf["block"], np.split(inverse, ends[:-1]), strict=True)]
        rows.append((-1, shard, None, int(counts.sum()), int((counts > 0).sum())))
        return pd.DataFrame(rows, columns=["block", "shard", "known", "n", "v"])

    return run


def _send_pairs(n_shards: int, total: int, distinct: int):  # noqa: ANN202
    """Base scores of a block's documents, and its pairs for each shard."""
    norm = float(total + distinct + 1)

    def run(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        rows: list[tuple] = []
        if len(left):
            block = int(left["block"].iloc[0])
            doc_ids, no_id, held, lens, place = load(left["tokens"].iloc[0])
            known = [load(x) for x in right.sort_values("shard")["known"]]
            number = np.concatenate([k for k, _ in known]).astype(np.uint64)
            count = np.concatenate([c for _, c in known]).astype(np.int64)
            token, lens = place.astype(np.int64), lens.astype(np.int64)
            starts = np.cumsum(lens) - lens
            base = np.add.reduceat(np.log10((count[token] + 1) / norm), starts)
            n_known = np.add.reduceat((count[token] > 0).astype(np.int64), starts)
            rows.append((block, block % n_shards, dump(doc_ids, no_id, held, tight(lens), tight(n_known), base), None))
            before = np.empty_like(token)
            before[1:] = token[:-1]
            before[starts] = token[starts[0] + lens[0] - 1]  # the end token
            doc = np.repeat(np.arange(len(lens)), lens)
            key = number[before] << np.uint64(32) | number[token]
            order = np.argsort(key, kind="stable")
            shard = ((key[order] * _MIX) >> np.uint64(40)) % np.uint64(n_shards)
            order = order[np.argsort(shard.astype(np.uint16 if n_shards < 1 << 16 else np.uint64), kind="stable")]
            key, doc, token, before = key[order], doc[order], token[order], before[order]
            shard = ((key * _MIX) >> np.uint64(40)) % np.uint64(n_shards)
            cuts = np.searchsorted(shard, np.arange(n_shards + 1, dtype=np.uint64))
            trained = (held[doc] == 0).astype(np.int64)
            for s in range(n_shards):
                a, b = int(cuts[s]), int(cuts[s + 1])
                if a < b:
                    first = _runs(key[a:b])
                    times = np.diff(np.append(first, b - a))
                    contexts = count[before[a:b][first]]
                    rows.append((block, s, None, dump(np.diff(key[a:b][first], prepend=np.uint64(0)), tight(times), tight(np.add.reduceat(trained[a:b], first)), tight(contexts), tight(count[token[a:b][first]]), tight(doc[a:b]))))
        return pd.DataFrame(rows, columns=["block", "shard", "base", "pairs"])

    return run


def _score_pairs(total: int, distinct: int, prior: float):  # noqa: ANN202
    norm = float(total + distinct + 1)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        rows: list[tuple] = [(int(b), x, None) for b, x in zip(pdf["block"], pdf["base"], strict=True) if x is not None]
        sent = [(int(b), load(x)) for b, x in zip(pdf["block"], pdf["pairs"], strict=True) if x is not None]
        if sent:
            keys, inverse = np.unique(np.concatenate([np.cumsum(x[0], dtype=np.uint64) for _, x in sent]), return_inverse=True)
            seen = np.bincount(inverse, np.concatenate([x[2] for _, x in sent]))
            of_context, of_word = np.empty(len(keys)), np.empty(len(keys))
            of_context[inverse], of_word[inverse] = np.concatenate([x[3] for _, x in sent]), np.concatenate([x[4] for _, x in sent])
            mass = prior * (of_word + 1) / norm
            context, word = keys >> np.uint64(32), keys & np.uint64((1 << 32) - 1)
            has = seen > 0
            log_p = np.log10(mass / (of_context + prior))  # of pairs that training lacks
            with tempfile.TemporaryFile() as f:
                f.write(elias_fano.build(context[has], word[has], np.log10((seen[has] + mass[has]) / (of_context[has] + prior))))
                f.flush()
                with mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ) as m:
                    trie = elias_fano.Trie(np.frombuffer(m, np.uint8))
                    found = trie.log_p(context, word)
                    del trie
            log_p = np.where(np.isnan(found), log_p, found)
            low = 0
            for block, x in sent:
                value = np.repeat(log_p[inverse[low : low + len(x[0])]], x[1])
                low += len(x[0])
                sums = np.bincount(x[5], value)
                at = np.flatnonzero(np.bincount(x[5]))
                rows.append((block, None, dump(tight(np.diff(at, prepend=0)), sums[at].astype(np.float32))))
        return pd.DataFrame(rows, columns=["block", "base", "part"])

    return run


def _sum_up(total: int):  # noqa: ANN202
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        doc_ids, no_id, held, lens, known, base = load(next(x for x in pdf["base"] if x is not None))
        score = np.zeros(len(doc_ids))
        for x in pdf["part"]:
            if x is not None:
                steps, sums = load(x)
                score[np.cumsum(steps, dtype=np.int64)] += sums
        ids = pd.array(doc_ids, dtype="Int64")
        ids[no_id.astype(bool)] = pd.NA
        return pd.DataFrame({"doc_id": ids, "held_out": held.astype(bool), "n_tokens": lens.astype(np.int64), "n_known": known.astype(np.int64), "train_tokens": total, "base_score": base, "score": score})

    return run


#: Counts in a trie are kept as log10 of their share of this; up to some 1,700 they come back exact, above to 0.03 %.
_WHOLE, _CHUNK = 15.0, 500_000


def _join_keys(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """A 64-bit key of two, in order."""
    x = (a ^ a >> np.uint64(32)) * _MIX + b * np.uint64(0xD6E8FEB86659FD93)
    x = (x ^ x >> np.uint64(29)) * np.uint64(0xBF58476D1CE4E5B9)
    return x ^ x >> np.uint64(32)


class _Grams:
    """A block's grams by order. keys: distinct ones, sent to shard key % n as key // n, ascending; of: for each token its gram's place in keys,
    -1 where its text has no context so long before it."""

    def __init__(self, tokens: bytes, words: bytes, order: int, n_shards: int):
        self.doc_ids, self.no_id, held, lens, place = load(tokens)
        self.held, self.lens = held.astype(bool), lens.astype(np.int64)
        self.starts = np.cumsum(self.lens) - self.lens
        hashes = np.cumsum(load(words)[0], dtype=np.uint64)[place]
        trained = np.repeat(~self.held, self.lens)
        at = np.arange(len(hashes)) - np.repeat(self.starts, self.lens)
        self.keys, self.cuts, self.of, self.trained = [], [], [], []
        gram, end = hashes, hashes[self.lens[0] - 1]
        for k in range(order):
            if k:
                before = np.empty_like(gram)
                before[1:] = gram[:-1]
                if k == 1:
                    before[self.starts] = end
                gram = _join_keys(before, hashes)
            has = np.flatnonzero(at >= k - 1)
            keys, inverse = np.unique(gram[has], return_inverse=True)
            shard = (keys % np.uint64(n_shards)).astype(np.int64)
            by_shard = np.argsort(shard.astype(np.uint16) if n_shards < 1 << 16 else shard, kind="stable")
            rank = np.empty(len(keys), np.int32)
            rank[by_shard] = np.arange(len(keys), dtype=np.int32)
            of = np.full(len(hashes), -1, np.int32)
            of[has] = rank[inverse]
            self.of.append(of)
            self.trained.append(np.bincount(of[has][trained[has]], minlength=len(keys)))
            self.keys.append((keys // np.uint64(n_shards))[by_shard])
            self.cuts.append(np.searchsorted(shard[by_shard], np.arange(n_shards + 1)))


def _send_grams(order: int, n_shards: int):  # noqa: ANN202
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = pa.schema([("block", pa.int64()), ("shard", pa.int32()), ("grams", pa.binary())])
        for batch in batches:
            for block, tokens, words in zip(*(batch.column(c).to_pylist() for c in ("block", "tokens", "words")), strict=True):
                x = _Grams(tokens, words, order, n_shards)
                for s in range(n_shards):
                    parts = [(keys[c[s] : c[s + 1]], t[c[s] : c[s + 1]]) for keys, c, t in zip(x.keys, x.cuts, x.trained, strict=True)]
                    # to each shard, also where it has no grams for it: a block adds up the totals of all shards
                    sent = dump(*(y for k, t in parts for y in (np.diff(k, prepend=np.uint64(0)), tight(t))))
                    yield pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip((block, s, sent), schema.types, strict=True)], schema=schema)

    return run


def _looked_up(keys: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Counts of ascending keys, from a trie of those that training has, mapped into memory: high bits lead to low ones."""
    high, low, has = keys >> np.uint64(24), keys & np.uint64((1 << 24) - 1), counts > 0
    out = np.zeros(len(keys), np.int64)
    with tempfile.TemporaryFile() as f:
        f.write(elias_fano.build(high[has], low[has], np.log10(counts[has]) - _WHOLE))
        f.flush()
        with mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ) as m:
            trie = elias_fano.Trie(np.frombuffer(m, np.uint8))
            for a in range(0, len(keys), _CHUNK):
                found = trie.log_p(high[a : a + _CHUNK], low[a : a + _CHUNK])
                out[a : a + _CHUNK] = np.rint(np.where(np.isnan(found), 0.0, 10 ** (found + _WHOLE)))
            del trie
    return out


def _count_grams(order: int):  # noqa: ANN202
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        blocks, sent = [int(b) for b in pdf["block"]], list(pdf["grams"])
        back: list[list[np.ndarray]] = [[] for _ in blocks]
        total = distinct = 0
        for k in range(order):
            keys, trained = [], []
            for x in sent:
                own = load(x)
                keys.append(np.cumsum(own[2 * k], dtype=np.uint64))
                trained.append(own[2 * k + 1])
            ends = np.cumsum([len(x) for x in keys])
            every, inverse = np.unique(np.concatenate(keys), return_inverse=True)
            del keys
            counts = np.bincount(inverse, np.concatenate(trained), len(every)).astype(np.int64)
            if k == 0:
                total, distinct = int(counts.sum()), int((counts > 0).sum())
            else:
                counts = _looked_up(every, counts)
            for out, at, t in zip(back, np.split(inverse, ends[:-1]), trained, strict=True):
                out.append(tight(np.maximum(counts[at] - t.astype(np.int64), 0)))  # by other blocks; takes less room
        shard = int(pdf["shard"].iloc[0])
        rows = [(b, shard, dump(*x), total, distinct) for b, x in zip(blocks, back, strict=True)]
        return pd.DataFrame(rows, columns=["block", "shard", "known", "n", "v"])

    return run


def _score_grams(order: int, n_shards: int, prior: float):  # noqa: ANN202
    def run(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        columns = ["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"]
        if not len(left):
            return pd.DataFrame([], columns=columns)
        x = _Grams(left["tokens"].iloc[0], left["words"].iloc[0], order, n_shards)
        known, total, distinct = [load(b) for b in right.sort_values("shard")["known"]], int(right["n"].sum()), int(right["v"].sum())
        if [sum(len(b[k]) for b in known) for k in range(order)] != [len(keys) for keys in x.keys]:
            raise ValueError("a block isn't the one whose grams were counted")
        count = [np.concatenate([b[k] for b in known]).astype(np.int64) + x.trained[k] for k in range(order)]
        one = count[0][x.of[0]]
        p = (one + 1) / float(total + distinct + 1)
        base = np.add.reduceat(np.log10(p), x.starts)
        context = np.empty_like(one)
        context[1:] = one[:-1]
        context[x.starts] = one[x.lens[0] - 1]  # the end token
        for k in range(1, order):
            has = np.flatnonzero(x.of[k] >= 0)
            grams = np.zeros_like(one)
            grams[has] = count[k][x.of[k][has]]
            p[has] = (grams[has] + prior * p[has]) / (context[has] + prior)
            context = np.r_[0, grams[:-1]]  # of the next order; the first words of texts have none
        ids = pd.array(x.doc_ids, dtype="Int64")
        ids[x.no_id.astype(bool)] = pd.NA
        known_words = np.add.reduceat((one > 0).astype(np.int64), x.starts)
        return pd.DataFrame(dict(zip(columns, (ids, x.held, x.lens, known_words, total, base, np.add.reduceat(np.log10(p), x.starts)), strict=True)))

    return run


def _score_by_grams(rows: DataFrame, order: int, n: int, prior: float, block_bytes: int, schema: str) -> DataFrame:
    # dealt by block once: the grams are made from this exchange, and the scores too, which reuse it; no block is written twice
    texts = rows.mapInArrow(_pack_blocks(0, block_bytes), "block bigint, shard int, tokens binary, words binary").select("block", "tokens", "words").repartition("block")
    sent = texts.mapInArrow(_send_grams(order, n), "block bigint, shard int, grams binary")
    known = sent.groupBy("shard").applyInPandas(_count_grams(order), "block bigint, shard int, known binary, n bigint, v bigint")
    return texts.groupBy("block").cogroup(known.groupBy("block")).applyInPandas(_score_grams(order, n, prior), schema)


def is_held_out(doc_id: str) -> F.Column:
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 7 == 2, F.lit(False))


_SCHEMA = "doc_id bigint, held_out boolean, n_tokens bigint, n_known bigint, train_tokens bigint, base_score double, score double"


def score(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", prior: float = PRIOR, block_bytes: int = BLOCK_BYTES, order: int = 2) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score: one row for each document. order: words of a gram, 2 at least."""
    if order < 2:
        raise ValueError("a gram has two words at least")
    n = partitions(docs.sparkSession)
    rows = docs.select(F.col(doc_id).cast("bigint").alias("doc_id"), is_held_out(doc_id).alias("held_out"), F.col(text).alias("text"))
    if order > 2:
        return _score_by_grams(rows, order, n, prior, block_bytes, _SCHEMA)
    blocks = keep(rows.mapInArrow(_pack_blocks(n, block_bytes), "block bigint, shard int, tokens binary, words binary"))
    counted = keep(blocks.where("shard >= 0").select("block", "shard", "words").groupBy("shard").applyInPandas(_count_words(n), "block bigint, shard int, known binary, n bigint, v bigint"))
    sums = counted.where("block = -1").agg(F.sum("n").alias("n"), F.sum("v").alias("v")).first()
    total, distinct = sums["n"] or 0, sums["v"] or 0
    texts = blocks.where("shard = -1").select("block", "tokens").groupBy("block")
    words = counted.where("block >= 0").select("block", "shard", "known").groupBy("block")
    pairs = texts.cogroup(words).applyInPandas(_send_pairs(n, total, distinct), "block bigint, shard int, base binary, pairs binary")
    parts = pairs.groupBy("shard").applyInPandas(_score_pairs(total, distinct, prior), "block bigint, base binary, part binary")
    return parts.groupBy("block").applyInPandas(_sum_up(total), _SCHEMA)

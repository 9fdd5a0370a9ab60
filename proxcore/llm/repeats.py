"""Exact removal of repeated byte strings: every byte that a WINDOW-byte string covers which also starts elsewhere.

Each window has an anchor, the leftmost least hash among its runs of GRAM bytes, so equal windows have equal anchors at
equal places. Consecutive windows of one anchor form a segment. The distinct segments of a block of texts travel as hashes to
the shard of their anchor. Segments of one anchor hash and one digest, 128 bits together, are one segment with a count: where
it is there twice, all its windows are repeated, which no order of suffixes needs to find. Distinct segments that share an
anchor may still share windows: their bytes are fetched, cut to what a neighbour in the order of left or right contexts
has in common with them, and a suffix array over all segments of the anchor finds the windows that follow one another as
equals. An anchor of more than HOT distinct segments is split: its windows go in steps of STEP places before the anchor,
and by what all windows of a step have in common, WINDOW - STEP + 1 bytes, so that equal windows still meet.

Texts are judged one by one: no match crosses documents. Results go back by the digest of a text, for equal texts have
equal results. No task gathers more than one block's results, or a share of the anchors with one entry for each block that
has a segment. A split anchor's segments that have the same 193 bytes still meet in one task, each distinct piece once for
each batch of texts.

Defined results: a null text is empty; a text shorter than a window loses nothing; a repeated row is a copy, so that a
text of a window's length or more that occurs twice is removed whole; strings are judged on the input; overlaps count.
"""

from __future__ import annotations

import hashlib
from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from proxcore.llm.common import keep, partitions, spread_join
from proxcore.llm.ngram_lm import dump, load, tight
from proxcore.llm.suffix_array import suffix_array

#: Bytes of a window and of an anchor; bytes of text in a block; windows that are anchored at a time.
WINDOW, GRAM, BLOCK_BYTES, STRETCH = 200, 64, 32_000_000, 1 << 22
#: Distinct segments of an anchor beyond which it is split, and the places of windows before the anchor in a step.
HOT, STEP = 512, 8
_MIX = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB)]
_BYTE = np.array([xxhash.xxh64_intdigest(bytes([b])) for b in range(256)], np.uint64)


def _gram_hashes(raw: np.ndarray) -> np.ndarray:
    """Of each run of GRAM bytes, by doubling."""
    h, width = _BYTE[raw], 1
    factor = int(_MIX[0])
    while width < GRAM:
        h = h[: len(h) - width] * np.uint64(factor) + h[width:]
        factor = factor * factor % (1 << 64)
        width *= 2
    h = (h ^ (h >> np.uint64(31))) * _MIX[1]
    return h ^ (h >> np.uint64(29))


def segments(raw: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Anchor hash, start of the first window and start of the last one, of each run of windows with one anchor."""
    n = len(raw) - WINDOW + 1
    parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    for low in range(0, max(0, n), STRETCH):
        k = min(STRETCH, n - low)
        h = _gram_hashes(np.frombuffer(raw, np.uint8, k + WINDOW - 1, low))
        least = (h & ~np.uint64((1 << 24) - 1)) | np.arange(len(h), dtype=np.uint64)  # of equals the leftmost
        width, span = 1, WINDOW - GRAM + 1
        while 2 * width <= span:
            least = np.minimum(least[:-width], least[width:])
            width *= 2
        least = np.minimum(least[:k], least[span - width : span - width + k])
        anchor = (least & np.uint64((1 << 24) - 1)).astype(np.int64)
        first = np.flatnonzero(np.concatenate([[True], anchor[1:] != anchor[:-1]]))
        parts.append((h[anchor[first]], first + low, np.append(first[1:], k) - 1 + low))
    if not parts:
        return np.empty(0, np.uint64), np.empty(0, np.int64), np.empty(0, np.int64)
    return tuple(np.concatenate(x) for x in zip(*parts, strict=True))  # type: ignore[return-value]


def _send(n_shards: int, block_bytes: int):  # noqa: ANN202
    def pack(block: int, marks: list[str], raws: list[bytes]) -> Iterator[tuple]:
        found = [segments(raw) for raw in raws]
        anchor, first, last = (np.concatenate([f[k] for f in found]) for k in range(3))
        doc = np.repeat(np.arange(len(raws)), [len(f[0]) for f in found])
        digest = np.fromiter((xxhash.xxh3_64_intdigest(raw[a : b + WINDOW]) for raw, (_, x, y) in zip(raws, found, strict=True) for a, b in zip(x.tolist(), y.tolist(), strict=True)), np.uint64, len(anchor))
        shard = (anchor >> np.uint64(20)) % np.uint64(n_shards)
        order = np.lexsort((digest, anchor, shard))  # of equals in order of text and place
        a, d = anchor[order], digest[order]
        head = np.flatnonzero(np.r_[True, (a[1:] != a[:-1]) | (d[1:] != d[:-1])])
        times = np.diff(np.append(head, len(order)))
        yield block, -1, "\n".join(marks).encode(), dump(tight(times), tight(doc[order]), tight(first[order]), tight((last - first)[order]))
        cuts = np.searchsorted(shard[order][head], np.arange(n_shards + 1, dtype=np.uint64))
        for s in range(n_shards):
            own = slice(cuts[s], cuts[s + 1])
            if cuts[s] < cuts[s + 1]:
                yield block, s, None, dump(np.diff(a[head[own]], prepend=np.uint64(0)), d[head[own]], tight(np.minimum(times[own], 2)), tight(np.arange(cuts[s], cuts[s + 1])))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number, size, marks, raws = TaskContext.get().partitionId() << 32, 0, [], []
        schema = pa.schema([("block", pa.int64()), ("shard", pa.int32()), ("marks", pa.binary()), ("sent", pa.binary())])

        def flush() -> Iterator[pa.RecordBatch]:
            for row in pack(number, marks, raws):
                yield pa.RecordBatch.from_arrays([pa.array([x], t) for x, t in zip(row, schema.types, strict=True)], schema=schema)

        for batch in batches:
            for mark, text in zip(batch.column("mark").to_pylist(), batch.column("text"), strict=True):
                raw = text.as_py().encode("utf-8", "surrogatepass")
                if len(raw) < WINDOW:
                    continue
                marks.append(mark)
                raws.append(raw)
                size += len(raw)
                if size >= block_bytes:
                    yield from flush()
                    number, size, marks, raws = number + 1, 0, [], []
        if raws:
            yield from flush()

    return run


def _by_block(block: np.ndarray, *arrays: np.ndarray) -> Iterator[tuple[int, bytes]]:
    order = np.argsort(block, kind="stable")
    at, first = np.unique(block[order], return_index=True)
    for b, own in zip(at.tolist(), np.split(order, first[1:]), strict=True):
        yield b, dump(*[x[own] for x in arrays])


def _match(pdf: pd.DataFrame, hot: int) -> pd.DataFrame:
    """What a shard knows: entries of segments that are there twice, and entries whose bytes are wanted."""
    parts = [load(x) for x in pdf["sent"]]
    block = np.repeat(pdf["block"].to_numpy(np.int64), [len(x[0]) for x in parts])
    anchor = np.concatenate([np.cumsum(x[0], dtype=np.uint64) for x in parts])
    digest, count, entry = (np.concatenate([x[k].astype(np.uint64 if k == 1 else np.int64) for x in parts]) for k in range(1, 4))
    order = np.lexsort((block, digest, anchor))
    block, anchor, digest, count, entry = (x[order] for x in (block, anchor, digest, count, entry))
    new_anchor = np.concatenate([[True], anchor[1:] != anchor[:-1]])
    new = new_anchor | np.concatenate([[True], digest[1:] != digest[:-1]])
    at = np.flatnonzero(new)  # distinct segments
    times = np.add.reduceat(count, at)
    twice = np.repeat(times > 1, np.diff(np.append(at, len(new))))
    # anchors with several distinct segments, one of which is there once
    number = np.cumsum(new_anchor[at]) - 1
    distinct = np.bincount(number)
    several = (distinct > 1) & (np.bincount(number, times == 1) > 0)
    chosen = np.flatnonzero(several[number])
    rows = [(b, x, None) for b, x in _by_block(block[twice], entry[twice])] if twice.any() else []
    if len(chosen):
        wanted = at[chosen]
        rows += [(b, None, x) for b, x in _by_block(block[wanted], anchor[wanted], entry[wanted], np.minimum(times[chosen], 2), distinct[number[chosen]] > hot)]
    return pd.DataFrame(rows, columns=["block", "spans", "wanted"])


def _return(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
    """By digest of the text: repeated spans, and segments that are wanted."""
    if not len(right):
        return pd.DataFrame([], columns=["mark", "spans", "wanted"])
    marks = left["marks"].iloc[0].decode().split("\n")
    times, doc, first, run = (x.astype(np.int64) for x in load(left["sent"].iloc[0]))
    head = np.cumsum(times) - times
    verdicts: dict[str, tuple[np.ndarray, ...]] = {}
    for name in ("spans", "wanted"):
        parts = [load(x) for x in right[name] if x is not None]
        if parts:
            verdicts[name] = tuple(np.concatenate([p[k] for p in parts]) for k in range(len(parts[0])))
    rows: dict[int, list] = {}
    if "spans" in verdicts:
        repeated = np.zeros(len(times), bool)
        repeated[verdicts["spans"][0]] = True
        every = np.repeat(repeated, times)
        d, f, r = doc[every], first[every], run[every]
        for k, own in _groups(d):
            rows.setdefault(k, [None, None])[0] = dump(*(tight(x) for x in _union(f[own], f[own] + r[own] + WINDOW)))
    if "wanted" in verdicts:
        anchor, entry, n, hot = verdicts["wanted"]
        at = head[entry]  # the first of the block's equal segments stands for them
        for k, own in _groups(doc[at]):
            own = own[np.argsort(first[at[own]], kind="stable")]
            rows.setdefault(k, [None, None])[1] = dump(anchor[own], tight(first[at[own]]), tight(run[at[own]]), tight(n[own]), tight(hot[own].astype(np.int64)))
    return pd.DataFrame([(marks[d], *x) for d, x in rows.items()], columns=["mark", "spans", "wanted"])


def _groups(doc: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    order = np.argsort(doc, kind="stable")
    at, first = np.unique(doc[order], return_index=True)
    yield from zip(at.tolist(), np.split(order, first[1:]), strict=True)


def _union(start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of intervals, those that touch are one."""
    order = np.argsort(start, kind="stable")
    start, end = start[order], np.maximum.accumulate(end[order])
    new = np.concatenate([[True], start[1:] > end[:-1]])
    at = np.flatnonzero(new)
    return start[at], end[np.append(at[1:], len(new)) - 1]


def _steps(anchor: int, piece: bytes, left: int, first: int) -> Iterator[tuple[int, int, int, bytes]]:
    """A segment of a split anchor: key, first, left and piece of the windows of each step."""
    low, windows = 0, len(piece) - WINDOW + 1
    while low < windows:
        step = (left - low) // STEP
        high = min(windows - 1, left - step * STEP)  # the last window whose place is in the step
        shared = piece[left - step * STEP : left - (step + 1) * STEP + 1 + WINDOW]  # whole even where the segment has a part of the step
        yield xxhash.xxh3_64_intdigest(shared, seed=anchor ^ step), first + low, left - low, piece[low : high + WINDOW]
        low = high + 1


def _cut_out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The bytes of wanted segments: anchor, mark, first, left (bytes before the anchor), piece, times. Where a batch has a
    piece of a split anchor several times, one row stands for all, as one that is there twice, and rows without a piece say
    at once what is repeated: first and, in place of left, the end."""
    for batch in batches:
        rows: list[tuple] = []
        split: dict[tuple[int, bytes], list[tuple]] = {}
        for k in range(batch.num_rows):
            mark, raw = batch.column("mark")[k].as_py(), batch.column("text")[k].as_py().encode("utf-8", "surrogatepass")
            for a, f, r, n, hot in zip(*(x.tolist() for x in load(batch.column("wanted")[k].as_py())), strict=True):
                piece = raw[f : f + r + WINDOW]
                left = int(np.flatnonzero(_gram_hashes(np.frombuffer(piece, np.uint8)) == np.uint64(a))[0])
                if not hot:
                    rows.append((a, mark, f, left, piece, n))
                    continue
                for key, first, own_left, part in _steps(a, piece, left, f):
                    split.setdefault((key, part), []).append((mark, first, own_left, n))
        for (key, part), found in split.items():
            mark, first, left, n = found[0]
            rows.append((key, mark, first, left, part, n if len(found) == 1 else 2))
            if len(found) > 1:  # spread by their own places
                rows += [(xxhash.xxh3_64_intdigest(m, seed=f), m, f, f + len(part), None, 1) for m, f, _, times in found if times == 1]
        anchor, mark, first, left, piece, times = zip(*rows, strict=True) if rows else [()] * 6
        yield pa.RecordBatch.from_arrays([pa.array(np.array(anchor, np.uint64).view(np.int64)), pa.array(mark, pa.string()), pa.array(first, pa.int64()), pa.array(left, pa.int64()), pa.array(piece, pa.binary()), pa.array(times, pa.int64())], ["anchor", "mark", "first", "left_bytes", "piece", "times"])


def _common(a: bytes, b: bytes) -> int:
    """Length of the common prefix."""
    n = min(len(a), len(b))
    if a[:n] == b[:n]:
        return n
    return bisect_left(range(n), True, key=lambda k: a[: k + 1] != b[: k + 1])


def _most_shared(contexts: list[bytes]) -> list[int]:
    """How much of its start each context has in common with any other: its neighbours in sorted order."""
    order = sorted(range(len(contexts)), key=contexts.__getitem__)
    out = [0] * len(contexts)
    for x, y in zip(order, order[1:], strict=False):
        n = _common(contexts[x], contexts[y])
        out[x], out[y] = max(out[x], n), max(out[y], n)
    return out


def repeated_windows(pieces: list[bytes], lefts: list[int]) -> list[list[int]]:
    """Of segments of one anchor: the starts of their windows that another one has too."""
    before = _most_shared([p[:k][::-1] for p, k in zip(pieces, lefts, strict=True)])
    after = _most_shared([p[k + GRAM :] for p, k in zip(pieces, lefts, strict=True)])
    text: list[int] = []
    owner: list[tuple[int, int, int, int]] = []  # place in the text, segment, start in the segment, windows
    raw = bytearray()
    for k, (piece, left) in enumerate(zip(pieces, lefts, strict=True)):
        start, end = left - before[k], left + GRAM + after[k]
        if end - start >= WINDOW:
            owner.append((len(text), k, start, end - start - WINDOW + 1))
            text += [b + 2 for b in piece[start:end]]
            text.append(1)
            raw += piece[start:end] + b"\0"
    out: list[list[int]] = [[] for _ in pieces]
    if len(owner) < 2:
        return out
    text.append(0)
    source: list[tuple[int, int] | None] = [None] * len(text)
    for at, k, start, n in owner:
        for d in range(n):
            source[at + d] = (k, start + d)
    last: bytes | None = None
    held: tuple[int, int] | None = None
    raw = bytes(raw)
    for p in suffix_array(text):
        if (of := source[p]) is not None:
            window = raw[p : p + WINDOW]
            if window == last:
                if held is not None:
                    out[held[0]].append(held[1])
                    held = None
                out[of[0]].append(of[1])
            else:
                last, held = window, of
    return out


def _resolve(pdf: pd.DataFrame) -> pd.DataFrame:
    """Repeated windows of a shard's segments, as spans by digest of the text."""
    known = pdf["piece"].isna()
    rows: list[tuple[str, int, int]] = list(pdf.loc[known, ["mark", "first", "left_bytes"]].itertuples(index=False, name=None))
    for _, own in pdf[~known].groupby("anchor", sort=False):
        if len(own) < 2:
            continue
        pieces, marks, first, times = own["piece"].tolist(), own["mark"].tolist(), own["first"].tolist(), own["times"].tolist()
        for k, found in enumerate(repeated_windows(pieces, own["left_bytes"].tolist())):
            if found and times[k] == 1:
                at = np.array(found, np.int64) + first[k]
                for a, b in zip(*(x.tolist() for x in _union(at, at + WINDOW)), strict=True):
                    rows.append((marks[k], a, b))
    return pd.DataFrame(rows, columns=["mark", "start", "end"])


SPANS = T.StructType([T.StructField("start", T.LongType()), T.StructField("end", T.LongType())])


def _apply(batches: Iterator[pa.RecordBatch], at: int, names: list[str], with_bytes: bool) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        n_bytes, removed, n_spans, digests, kept_bytes, all_spans = [], [], [], [], [], []
        for text, packed, more in zip(batch.column(at), batch.column("__spans"), batch.column("__more"), strict=True):
            raw = (text.as_py() or "").encode("utf-8", "surrogatepass")
            start, end = [], []
            if (x := packed.as_py()) is not None:
                a, b = load(x)
                start, end = a.astype(np.int64).tolist(), b.astype(np.int64).tolist()
            for s in more.as_py() or ():
                start.append(s["start"])
                end.append(s["end"])
            spans = list(zip(*(x.tolist() for x in _union(np.array(start, np.int64), np.array(end, np.int64))), strict=True)) if start else []
            kept, low = [], 0
            for a, b in spans:
                kept.append(raw[low:a])
                low = b
            kept = b"".join([*kept, raw[low:]])
            n_bytes.append(len(raw))
            removed.append(len(raw) - len(kept))
            n_spans.append(len(spans))
            digests.append(hashlib.sha256(kept).hexdigest())
            if with_bytes:
                kept_bytes.append(kept)
                all_spans.append([{"start": a, "end": b} for a, b in spans])
        columns = [batch.column(c) for c in names] + [pa.array(n_bytes, pa.int64()), pa.array(removed, pa.int64()), pa.array(n_spans, pa.int64()), pa.array(digests, pa.string())]
        labels = [*names, "n_bytes", "n_removed", "n_spans", "kept_sha256"]
        if with_bytes:
            columns += [pa.array(all_spans, pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))), pa.array(kept_bytes, pa.binary())]
            labels += ["spans", "kept"]
        yield pa.RecordBatch.from_arrays(columns, labels)


def remove_repeats(docs: DataFrame, *, text: str = "text", columns: list[str] | None = None, with_bytes: bool = False, block_bytes: int = BLOCK_BYTES, hot: int = HOT) -> DataFrame:
    """The given columns (all but the text by default) with n_bytes, n_removed, n_spans, kept_sha256; with_bytes adds spans and kept."""
    spark = docs.sparkSession
    n = partitions(spark)
    names = columns if columns is not None else [c for c in docs.columns if c != text]
    rows = docs.select(*names, F.col(text).alias("__text")).withColumn("__mark", F.md5("__text"))
    texts = rows.where("__text is not null").select(F.col("__mark").alias("mark"), F.col("__text").alias("text"))
    sent = keep(texts.mapInArrow(_send(n, block_bytes), "block bigint, shard int, marks binary, sent binary"))
    matched = sent.where("shard >= 0").select("block", "shard", "sent").groupBy("shard").applyInPandas(lambda pdf: _match(pdf, hot), "block bigint, spans binary, wanted binary")
    returned = sent.where("shard = -1").select("block", "marks", "sent").groupBy("block").cogroup(matched.groupBy("block")).applyInPandas(_return, "mark string, spans binary, wanted binary")
    known = keep(returned.groupBy("mark").agg(F.max("spans").alias("spans"), F.max("wanted").alias("wanted")))
    wanted = known.where("wanted is not null").select(F.col("mark").alias("of"), "wanted")
    one_each = texts.join(wanted.select("of"), F.col("mark") == F.col("of"), "left_semi").groupBy("mark").agg(F.first("text").alias("text"))
    pieces = one_each.join(wanted, F.col("mark") == F.col("of")).select("mark", "text", "wanted").mapInArrow(_cut_out, "anchor bigint, mark string, first bigint, left_bytes bigint, piece binary, times bigint")
    more = pieces.groupBy(F.pmod(F.xxhash64("anchor"), F.lit(8 * n)).alias("share")).applyInPandas(_resolve, "mark string, start bigint, end bigint")
    more = more.groupBy("mark").agg(F.collect_list(F.struct("start", "end")).alias("__more")).withColumnRenamed("mark", "__m")
    spans = known.where("spans is not null").select(F.col("mark").alias("__k"), F.col("spans").alias("__spans"))
    both = spans.join(more, F.col("__k") == F.col("__m"), "full").select(F.coalesce("__k", "__m").alias("__of"), "__spans", "__more")
    joined = spread_join(rows, both.withColumnRenamed("__of", "__which"), "__mark", "__which", "left").select(*names, "__text", "__spans", "__more")
    schema = T.StructType([*docs.select(*names).schema.fields, *[T.StructField(c, T.LongType()) for c in ("n_bytes", "n_removed", "n_spans")], T.StructField("kept_sha256", T.StringType())])
    if with_bytes:
        schema = T.StructType([*schema.fields, T.StructField("spans", T.ArrayType(SPANS)), T.StructField("kept", T.BinaryType())])
    return joined.mapInArrow(lambda batches: _apply(batches, len(names), names, with_bytes), schema)

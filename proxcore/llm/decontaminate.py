"""Benchmark decontamination: one Aho-Corasick automaton over normalised benchmark windows, each text scanned once.

Words are maximal runs of digits, ASCII letters (lower-cased) and non-ASCII bytes. An item's windows are its runs of
`window` consecutive words; an item of fewer words, but not none, is one window. The automaton works on word numbers
rather than letters, so that it has one node for each word of a window and can't match inside a word.

Defined results: a null or wordless text has no words and no hits; an item without words or with a null id is
ignored; repeated items count once; repeated documents are each judged. The benchmark is read in blocks of at most
`block_words` words, each broadcast on its own, so what is broadcast doesn't grow with the benchmark.
"""

from __future__ import annotations

import re
from collections import defaultdict
from itertools import repeat

import ahocorasick
import numpy as np
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from proxcore.llm.common import with_struct

#: Separators become blanks, A-Z become a-z; all bytes of a non-ASCII character are letters of words.
_FOLD = bytes(b if b >= 0x80 or 0x30 <= b <= 0x39 or 0x61 <= b <= 0x7A else b + 32 if 0x41 <= b <= 0x5A else 0x20 for b in range(256))
_RUN = re.compile(rb"[^ ]+")
#: The words pattern for Spark's own functions.
WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"

HITS = T.StructType([
    T.StructField("n_words", T.LongType()), T.StructField("n_hit", T.LongType()), T.StructField("item_ids", T.ArrayType(T.StringType())),
    T.StructField("spans", T.ArrayType(T.StructType([T.StructField("start", T.LongType()), T.StructField("end", T.LongType())]))),
])


def folded(text: str) -> bytes:
    return text.encode("utf-8", "surrogatepass").translate(_FOLD)


class Automaton:
    """Over the windows of items: (id, text) pairs."""

    def __init__(self, items: list[tuple[str, str]], window: int):
        self.number: dict[bytes, int] = {}
        owners: dict[tuple[int, ...], set[str]] = defaultdict(set)
        for item, text in items:
            ids = tuple(self.number.setdefault(w, len(self.number) + 1) for w in folded(text).split())
            for k in range(max(1, len(ids) - window + 1) if ids else 0):
                owners[ids[k : k + window]].add(item)
        self.empty = not owners
        self.search = ahocorasick.Automaton(ahocorasick.STORE_ANY, ahocorasick.KEY_SEQUENCE)
        for key, of in owners.items():
            self.search.add_word(key, (len(key), of))
        self.search.make_automaton()

    def scan(self, text: str | None) -> dict:
        """Counts of words and hit words, items found, and the hit runs as character offsets of the given text."""
        flat = folded(text or "")
        words = flat.split()
        hit, found = bytearray(len(words)), set()
        if words and not self.empty:
            for end, (n, of) in self.search.iter(tuple(map(self.number.get, words, repeat(0)))):
                hit[end - n + 1 : end + 1] = b"\x01" * n
                found |= of
        return {"n_words": len(words), "n_hit": hit.count(1), "item_ids": sorted(found), "spans": _spans(text, flat, hit) if found else []}


def _spans(text: str, flat: bytes, hit: bytearray) -> list[dict]:
    at = np.array([m.span() for m in _RUN.finditer(flat)], np.int64)
    flags = np.frombuffer(bytes(hit), np.uint8).astype(np.int8)
    step = np.diff(flags, prepend=0, append=0)
    first, last = np.flatnonzero(step == 1), np.flatnonzero(step == -1) - 1
    raw = np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)
    chars = np.concatenate([[0], np.cumsum((raw & 0xC0) != 0x80)])
    return [{"start": int(a), "end": int(b)} for a, b in zip(chars[at[first, 0]], chars[at[last, 1]], strict=True)]


_built: dict[object, Automaton] = {}


def _automaton(items: Broadcast, window: int) -> Automaton:
    """One for each worker and block."""
    key = (items.value[0], window)
    if key not in _built:
        if len(_built) > 2:
            _built.clear()
        _built[key] = Automaton(items.value[1], window)
    return _built[key]


def _blocks(benchmark: DataFrame, item_id: str, text: str, block_words: int) -> tuple[DataFrame, int]:
    items = benchmark.select(F.col(item_id).cast("string").alias("item"), F.col(text).alias("words")).where("item is not null and words is not null")
    total = items.agg(F.sum(F.length("words")).alias("n")).first()["n"] or 0
    n = 1 + total // (4 * block_words)
    return items.withColumn("block", F.pmod(F.xxhash64("item"), F.lit(n))), n


def scan(docs: DataFrame, benchmark: DataFrame, *, text: str = "text", item_id: str = "item_id", item_text: str = "text", window: int = 13, block_words: int = 500_000, out: str = "hits") -> DataFrame:
    """docs with the struct column `out` (HITS). With several blocks of items their hits are united within the row."""
    items, n = _blocks(benchmark, item_id, item_text, block_words)
    spark = docs.sparkSession
    for k in range(n):
        rows = items.where(F.col("block") == k).select("item", "words").collect()  # at most about block_words words
        sent = spark.sparkContext.broadcast((f"{id(items)}-{k}-{hash(tuple(rows))}", [tuple(r) for r in rows]))
        name = out if n == 1 else f"{out}__{k}"
        docs = with_struct(docs, text, name, HITS, lambda texts, sent=sent: [_automaton(sent, window).scan(x) for x in texts])
    if n > 1:
        docs = _united(docs, text, out, [f"{out}__{k}" for k in range(n)])
    return docs


def _united(docs: DataFrame, text: str, out: str, parts: list[str]) -> DataFrame:
    """Hit words are counted anew over the union of the blocks' spans."""
    docs = docs.withColumn("__spans", F.array_sort(F.concat(*[f"{p}.spans" for p in parts])))
    docs = docs.withColumn("__spans", F.aggregate("__spans", F.array().cast("array<struct<start:bigint,end:bigint>>"), lambda a, s: F.when((F.size(a) > 0) & (F.element_at(a, -1)["end"] >= s["start"]), F.concat(F.slice(a, 1, F.greatest(F.size(a) - 1, F.lit(0))), F.array(F.struct(F.element_at(a, -1)["start"].alias("start"), F.greatest(F.element_at(a, -1)["end"], s["end"]).alias("end"))))).otherwise(F.concat(a, F.array(s)))))
    words = F.aggregate("__spans", F.lit(0).cast("bigint"), lambda n, s: n + F.regexp_count(F.lower(F.substring(F.col(text), (s["start"] + 1).cast("int"), (s["end"] - s["start"]).cast("int"))), F.lit(WORD)))
    return docs.withColumn(out, F.struct(F.col(f"{parts[0]}.n_words").alias("n_words"), words.alias("n_hit"), F.array_sort(F.array_distinct(F.concat(*[f"{p}.item_ids" for p in parts]))).alias("item_ids"), F.col("__spans").alias("spans"))).drop("__spans", *parts)


def is_contaminated(hits: str = "hits") -> F.Column:
    """A twentieth of the words, at least one, are hit."""
    return (F.col(f"{hits}.n_hit") > 0) & (20 * F.col(f"{hits}.n_hit") >= F.col(f"{hits}.n_words"))


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, **how: object) -> DataFrame:
    return scan(docs, benchmark, out="__hits", **how).where(~is_contaminated("__hits")).drop("__hits")

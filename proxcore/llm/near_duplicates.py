"""Near-duplicate classes by consistent weighted sampling over TF-IDF shingles, banded, verified by weighted Jaccard.

A text's vector has one weight for each of its runs of five words: occurrences times an inverse document frequency,
log(1 + N / df) to the power DAMPING. Document frequencies come from all documents: each part of them counts its shingles in a
table of CELLS cells, the tables are added up in two rounds, and what other shingles add to a cell on average is taken off. So
the frequencies have one fixed size at any size of the corpus, and an error of about the mean number of shingles in a
document over CELLS, as a share of the documents: shingles rarer than that (one document in some ten thousand) weigh
alike, the rest by their frequency. The power keeps passages of large clusters from weighing almost nothing beside a changed
word: with plain logarithms a text loses its cluster by one edit once a third of the documents are in it.

Samples are drawn by improved consistent weighted sampling in the logarithmic domain: for each shingle and hash a pair of
Gamma(2, 1) draws and a uniform one follow from the hashed shingle; the least score of a text is its sample, equal for two
texts with the probability of their weighted Jaccard similarity. BANDS bands of ROWS samples, and the bands in pairs,
form buckets. First each text is verified against the partner it meets most often among the least members of its buckets.
Then, in rounds, the least members of each bucket (HUBS, then HUBS_MORE times as many as before) are verified against all its others
that are in another component and go out of the bucket, until every bucket is within one component. In a bucket of more than
HUBS + 1 members, a text goes out first, and a pair isn't verified, if what its shingles have in common with texts of other
components weighs too little for LEAST, whatever the other text is. So each two members of a bucket are verified, already
linked, or proved unlike; pairs grow with the square of a bucket only where its members aren't alike and the bound doesn't say so.
Links are closed into components.

Defined results: texts that are equal and have a word form one class; a text of one to four words has one shingle; null,
empty and wordless texts are classes of their own; a row with a null id gets a null class; rows that repeat an id are one
document, whose text is the one with the least digest.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from proxcore.llm.common import keep, partitions, spread_join
from proxcore.llm.components import components
from proxcore.llm.decontaminate import folded
from proxcore.llm.ngram_lm import dump, load, tight

WIDTH, LEAST, DAMPING = 5, 0.8, 0.5
#: Cells of the document frequencies and of one message of them.
CELLS, CHUNK = 1 << 22, 1 << 16
BANDS, ROWS, HUBS, HUBS_MORE = 16, 4, 16, 16
#: Room for rounding in the bounds of a similarity.
SLACK = 1 + 1e-9
_MIX = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F)]
_SHIFT = np.uint64(32)


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> _SHIFT)) * _MIX[1]
    x = (x ^ (x >> np.uint64(29))) * _MIX[2]
    return x ^ (x >> _SHIFT)


def shingles(text: str | None, width: int = WIDTH) -> np.ndarray:
    """Hashes of the runs of `width` words, in order; one for a shorter text."""
    words = folded(text or "").split()
    if not words:
        return np.empty(0, np.uint64)
    w = np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))
    n = max(1, len(w) - width + 1)
    out = np.zeros(n, np.uint64)
    with np.errstate(over="ignore"):
        for k in range(min(width, len(w))):
            out = out * _MIX[0] + w[k : k + n] * _MIX[3 + k % 2]
        return mixed(out)


def _gamma_two() -> np.ndarray:
    """Quantiles of Gamma(2, 1) at 4096 midpoints, by bisection of 1 - (1 + x) exp(-x)."""
    q, low, high = (np.arange(4096) + 0.5) / 4096, np.zeros(4096), np.full(4096, 60.0)
    for _ in range(80):
        mid = (low + high) / 2
        under = 1 - (1 + mid) * np.exp(-mid) < q
        low, high = np.where(under, mid, low), np.where(under, high, mid)
    return high


_GAMMA = _gamma_two()
_LOG_GAMMA = np.log(_GAMMA)


class Weights:
    """Inverse document frequencies by cell; cells may be fewer than CELLS, for tests."""

    def __init__(self, cells: np.ndarray, documents: int, damping: float = DAMPING):
        self.size = np.uint64(len(cells))
        self.idf, total = np.empty(len(cells), np.float32), float(cells.sum())
        for low in range(0, len(cells), CHUNK):  # a chunk at a time, for the driver holds this
            counts = cells[low : low + CHUNK].astype(np.float64)
            noise = (total - counts) / max(1, len(cells) - 1)
            df = np.clip(counts - noise, 1.0, max(1, documents))
            self.idf[low : low + CHUNK] = np.log1p(max(1, documents) / df) ** damping

    def vector(self, text: str | None) -> tuple[np.ndarray, np.ndarray]:
        """Sorted shingles and their weights."""
        keys, counts = np.unique(shingles(text), return_counts=True)
        return keys, counts * self.idf[(keys % self.size).astype(np.int64)].astype(np.float64)


def samples(vectors: list[tuple[np.ndarray, np.ndarray]], n: int = BANDS * ROWS) -> np.ndarray:
    """A row of n samples for each vector, none of which may be empty."""
    out = np.empty((len(vectors), n), np.uint64)
    seeds = mixed(np.arange(1, n + 1, dtype=np.uint64) * _MIX[0])
    low = 0
    while low < len(vectors):  # blocks that stay in the cache
        high, size = low, 0
        while high < len(vectors) and (high == low or size + len(vectors[high][0]) <= 16_384):
            size += len(vectors[high][0])
            high += 1
        keys = np.concatenate([k for k, _ in vectors[low:high]])
        log_w = np.log(np.concatenate([w for _, w in vectors[low:high]]))
        plain = not log_w.any()
        starts = np.cumsum([0, *[len(k) for k, _ in vectors[low : high - 1]]])
        for k in range(n):
            u = (keys ^ seeds[k]) * _MIX[1]
            u = (u ^ (u >> _SHIFT)) * _MIX[2]
            r = _GAMMA[(u >> np.uint64(52)).view(np.int64)]
            c = _LOG_GAMMA[((u >> np.uint64(40)) & np.uint64(4095)).view(np.int64)]
            beta = ((u ^ (u >> _SHIFT)) & np.uint64((1 << 40) - 1)) * 2.0**-40
            step = np.floor(beta) if plain else np.floor(log_w / r + beta)
            out[low:high, k] = np.minimum.reduceat(c - r * (step - beta + 1), starts).view(np.uint64)
        low = high
    return out


def band_keys(sample: np.ndarray) -> np.ndarray:
    """Of rows of samples: keys of the bands, then of the bands in pairs."""
    n = sample.shape[0]
    with np.errstate(over="ignore"):
        fold = np.zeros((n, BANDS), np.uint64)
        for k in range(ROWS):
            fold = mixed(fold * _MIX[0] + sample.reshape(n, BANDS, ROWS)[:, :, k])
        fold = mixed(fold + np.arange(BANDS, dtype=np.uint64) * _MIX[4])
        return np.concatenate([fold, mixed(fold[:, ::2] * _MIX[0] + fold[:, 1::2])], axis=1)


def similarity(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    """Weighted Jaccard of two vectors."""
    if not len(a[0]) or not len(b[0]):
        return 0.0
    at = np.minimum(np.searchsorted(a[0], b[0]), len(a[0]) - 1)
    met = a[0][at] == b[0]
    both = np.minimum(a[1][at[met]], b[1][met]).sum()
    total = a[1].sum() + b[1].sum() - both
    return float(both / total) if total else 0.0


def _count_cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """chunk, part, cells, docs: in how many of a part's documents a shingle of each cell is; one row has the number of documents."""
    cells, held, size, docs = np.zeros(CELLS, np.uint32), [], 0, 0
    part = TaskContext.get().partitionId()

    def add() -> None:
        nonlocal held, size
        at, n = np.unique(np.concatenate(held), return_counts=True)
        cells[at.astype(np.int64)] += n.astype(np.uint32)
        held, size = [], 0

    for batch in batches:
        for text in batch.column("text"):
            held.append(np.unique(shingles(text.as_py())) % np.uint64(CELLS))
            size += len(held[-1])
            docs += 1
            if size > 1_000_000:
                add()
    if held:
        add()
    if docs:
        yield _cell_rows({k: cells[k * CHUNK : (k + 1) * CHUNK] for k in range(CELLS // CHUNK) if cells[k * CHUNK : (k + 1) * CHUNK].any()}, part, docs)


def _cell_rows(chunks: dict[int, np.ndarray], part: int, docs: int) -> pa.RecordBatch:
    rows = [(k, part, dump(tight(x)), 0) for k, x in sorted(chunks.items())] + [(-1, part, None, docs)]
    return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.int32()), pa.array([r[2] for r in rows], pa.binary()), pa.array([r[3] for r in rows], pa.int64())], ["chunk", "part", "cells", "docs"])


def _add_cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The same with all rows of a chunk that a task meets as one; holds CELLS cells at most."""
    chunks: dict[int, np.ndarray] = {}
    docs, part = 0, TaskContext.get().partitionId()
    for batch in batches:
        for k, cells, n in zip(batch.column("chunk").to_pylist(), batch.column("cells"), batch.column("docs").to_pylist(), strict=True):
            docs += n
            if k >= 0:
                fresh = load(cells.as_py())[0].astype(np.uint64)
                chunks[k] = chunks[k] + fresh if k in chunks else fresh
    if chunks or docs:
        yield _cell_rows(chunks, part, docs)


def weights(texts: DataFrame, damping: float = DAMPING) -> Weights:
    """From a table of texts, one row for each document."""
    kind, n = "chunk int, part int, cells binary, docs bigint", partitions(texts.sparkSession)
    rows = texts.select("text").mapInArrow(_count_cells, kind)
    for by in ([F.col("chunk"), F.pmod("part", F.lit(n))], [F.col("chunk")]):
        rows = rows.repartition(n, *by).mapInArrow(_add_cells, kind)
    cells, docs = np.zeros(CELLS, np.uint64), 0
    for r in keep(rows).toLocalIterator():  # CELLS cells, whatever the size of the table
        docs += r["docs"]
        if r["chunk"] >= 0:
            cells[r["chunk"] * CHUNK : (r["chunk"] + 1) * CHUNK] += load(bytes(r["cells"]))[0].astype(np.uint64)
    return Weights(cells, docs, damping)


def _buckets(keys: DataFrame) -> DataFrame:
    """key, id: members of the buckets that have more than one."""
    rows = keys.select(F.explode("keys").alias("key"), "id")
    return keep(rows.join(rows.groupBy("key").agg(F.count("*").alias("n")).where("n > 1").select("key"), "key", "left_semi"))


def _verified(pairs: DataFrame, texts: DataFrame, sent, least: float) -> DataFrame:  # noqa: ANN001
    """The pairs whose texts are similar enough."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own: Weights = sent.value
        held: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        size = 0

        def vector(i: int, text: pa.Scalar) -> tuple[np.ndarray, np.ndarray]:
            nonlocal size
            if i not in held:
                if size > 2_000_000:
                    held.clear()
                    size = 0
                held[i] = own.vector(text.as_py())
                size += len(held[i][0])
            return held[i]

        for batch in batches:
            a, b, good = batch.column("a").to_pylist(), batch.column("b").to_pylist(), []
            for k in range(batch.num_rows):
                good.append(similarity(vector(a[k], batch.column("text_a")[k]), vector(b[k], batch.column("text_b")[k])) >= least)
            at = pa.array(good, pa.bool_())
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()).filter(at), pa.array(b, pa.int64()).filter(at)], ["a", "b"])

    one = pairs.select("a", "b").join(texts.select(F.col("id").alias("b"), F.col("text").alias("text_b")), "b")
    two = one.join(texts.select(F.col("id").alias("a"), F.col("text").alias("text_a")), "a")
    return two.select("a", "b", "text_a", "text_b").mapInArrow(run, "a bigint, b bigint")


def _bounds(members: DataFrame, texts: DataFrame, sent) -> DataFrame:  # noqa: ANN001
    """id, total, shared of members (id, root): the weight of a text, and of its shingles that a text of another component has too;
    texts without such a shingle have no row. What two texts of different components have in common weighs no more than either's
    shared."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own: Weights = sent.value
        for batch in batches:
            for low in range(0, batch.num_rows, 256):
                part = batch.slice(low, 256)
                made = [own.vector(x.as_py()) for x in part.column("text")]
                at = pa.array(np.repeat(np.arange(len(made)), [len(k) for k, _ in made]))
                total = np.array([w.sum() for _, w in made])
                columns = [part.column("id").take(at), part.column("root").take(at), pa.array(np.concatenate([k for k, _ in made]).view(np.int64)), pa.array(np.concatenate([w for _, w in made])), pa.array(total).take(at)]
                yield pa.RecordBatch.from_arrays(columns, ["id", "root", "shingle", "weight", "total"])

    rows = keep(members.join(texts, "id").select("id", "root", "text").mapInArrow(run, "id bigint, root bigint, shingle bigint, weight double, total double"))
    common = rows.groupBy("shingle").agg(F.min("root").alias("low"), F.max("root").alias("high")).where("low < high").select("shingle")
    return rows.join(common, "shingle", "left_semi").groupBy("id").agg(F.first("total").alias("total"), F.sum("weight").alias("shared"))


def _mixed(buckets: DataFrame) -> DataFrame:
    """Rows of the buckets (key, id, root) that have more than one component, with the number of their members."""
    sizes = buckets.groupBy("key").agg(F.min("root").alias("low"), F.max("root").alias("high"), F.count("*").alias("n"))
    return buckets.join(sizes.where("low < high").select("key", "n"), "key")


def _open(buckets: DataFrame, roots: DataFrame, texts: DataFrame, sent, least: float) -> DataFrame:  # noqa: ANN001
    """key, id, root, total, shared of the buckets of more than one component. From those of more than HUBS + 1 members go the texts
    that by their bounds are like none of another component; total and shared are null elsewhere."""
    named = buckets.join(roots, F.col("id") == F.col("node"), "left").select("key", "id", F.coalesce("root", "id").alias("root"))
    mixed = keep(_mixed(named))
    large = mixed.where(F.col("n") > HUBS + 1).drop("n")
    none = F.lit(None).cast("double")
    small = mixed.where(F.col("n") <= HUBS + 1).drop("n").withColumns({"total": none, "shared": none})
    if large.isEmpty():
        return small
    bounds = keep(_bounds(large.select("id", "root").distinct(), texts, sent).where(F.col("shared") * SLACK >= least * F.col("total")))
    return keep(small.unionByName(_mixed(large.join(bounds, "id")).drop("n")))


def _roots(buckets: DataFrame, texts: DataFrame, sent, least: float) -> DataFrame:  # noqa: ANN001
    """node, root: components of the links among members of a bucket."""
    hubs = buckets.groupBy("key").agg(F.min("id").alias("a"))
    met = buckets.join(hubs, "key").where("id <> a").groupBy("a", F.col("id").alias("b")).agg(F.count("*").alias("n"))
    tried = keep(met.groupBy("b").agg(F.max_by("a", F.struct("n", -F.col("a"))).alias("a")).select("a", "b"))
    links = keep(_verified(tried, texts, sent, least))
    roots, width = keep(components(links)), HUBS
    while True:
        buckets = _open(buckets, roots, texts, sent, least)
        if buckets.isEmpty():
            return roots
        rank = F.row_number().over(Window.partitionBy("key").orderBy("id"))
        hubs = keep(buckets.withColumn("rank", rank).where(F.col("rank") <= width).select("key", F.col("id").alias("a"), F.col("root").alias("root_a"), F.col("total").alias("total_a"), F.col("shared").alias("shared_a")))
        # similar texts have at least this in common
        enough = F.col("total").isNull() | (F.least("shared", "shared_a") * SLACK >= least / (1 + least) * (F.col("total") + F.col("total_a")))
        pairs = keep(hubs.join(buckets, "key").where("a < id and root_a <> root").where(enough).select("a", F.col("id").alias("b")).distinct().join(tried, ["a", "b"], "left_anti"))
        fresh = keep(_verified(pairs, texts, sent, least))
        tried = tried.unionByName(pairs)
        if not fresh.isEmpty():
            links = links.unionByName(fresh)
            roots = keep(components(links))
        # a hub has met all of its bucket
        buckets = buckets.select("key", "id").join(hubs.select("key", F.col("a").alias("id")), ["key", "id"], "left_anti")
        width *= HUBS_MORE


def _judged(docs: DataFrame, doc_id: str, text: str, least: float, damping: float) -> DataFrame:
    """id, mark, class_id: one row for each document, with the digest of the text it was judged by."""
    spark = docs.sparkSession
    rows = docs.select(F.col(doc_id).cast("bigint").alias("id"), F.col(text).alias("text")).where("id is not null").withColumn("mark", F.md5(F.coalesce("text", F.lit(""))))
    sent = spark.sparkContext.broadcast(weights(rows, damping))

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own: Weights = sent.value
        for batch in batches:
            for low in range(0, batch.num_rows, 256):
                part = batch.slice(low, 256)
                vectors = [own.vector(x.as_py()) for x in part.column("text")]
                has = [k for k, v in enumerate(vectors) if len(v[0])]
                made: list = [None] * len(vectors)
                if has:
                    for k, row in zip(has, band_keys(samples([vectors[k] for k in has])).view(np.int64), strict=True):
                        made[k] = row
                yield pa.RecordBatch.from_arrays([part.column("id"), part.column("mark"), pa.array(made, pa.list_(pa.int64()))], ["id", "mark", "keys"])

    signed = keep(rows.mapInArrow(sign, "id bigint, mark string, keys array<bigint>"))
    ids = keep(signed.groupBy("id").agg(F.min("mark").alias("mark")))
    reps = keep(ids.groupBy("mark").agg(F.min("id").alias("rep")))
    keys = signed.where("keys is not null").join(reps.withColumnRenamed("mark", "of"), (F.col("id") == F.col("rep")) & (F.col("mark") == F.col("of"))).groupBy("id").agg(F.first("keys").alias("keys"), F.first("mark").alias("mark"))
    keys = keep(keys)
    buckets = _buckets(keys)
    # texts are shuffled once, and of the members of buckets alone; equal rows of an id are one
    met = buckets.select(F.col("id").alias("of")).distinct().join(keys.select(F.col("id").alias("of"), F.col("mark").alias("its")), "of")
    texts = keep(rows.join(met, (F.col("id") == F.col("of")) & (F.col("mark") == F.col("its"))).groupBy("id").agg(F.first("text").alias("text")))
    roots = _roots(buckets, texts, sent, least)
    # equal texts with a word share their representative's class; wordless ones keep their own
    named_marks = reps.join(keys.select(F.col("id").alias("has")), F.col("rep") == F.col("has")).join(roots, F.col("rep") == F.col("node"), "left").select(F.col("mark").alias("of"), F.coalesce("root", "rep").alias("class_id"))
    return spread_join(ids, named_marks, "mark", "of", "left").select("id", "mark", F.coalesce("class_id", "id").alias("class_id"))


def classes(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", least: float = LEAST, damping: float = DAMPING) -> DataFrame:
    """doc_id, class_id (the least id of its class): one row for each document."""
    judged = _judged(docs, doc_id, text, least, damping).select("id", "class_id")
    if docs.where(F.col(doc_id).isNull()).limit(1).count():
        judged = judged.unionByName(docs.where(F.col(doc_id).isNull()).select(F.lit(None).cast("bigint").alias("id"), F.lit(None).cast("bigint").alias("class_id")))
    return judged.withColumnRenamed("id", doc_id) if doc_id != "class_id" else judged


def drop_near_duplicates(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", least: float = LEAST, damping: float = DAMPING) -> DataFrame:
    """Of each class the document of the least id; of rows that repeat an id one, with the text that was judged; rows without an
    id stay."""
    chosen = _judged(docs, doc_id, text, least, damping).where("id = class_id").select(F.col("id").alias("__chosen"), F.col("mark").alias("__mark"))
    same = (F.col(doc_id) == F.col("__chosen")) & (F.md5(F.coalesce(F.col(text), F.lit(""))) == F.col("__mark"))
    named = docs.where(F.col(doc_id).isNotNull()).join(chosen, same).drop("__chosen", "__mark").dropDuplicates([doc_id])
    return named.unionByName(docs.where(F.col(doc_id).isNull()))

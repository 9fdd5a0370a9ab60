"""One query for each corpus operator over its whole table, and the SQL of those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from proxcore.llm import bpe, chat, decontaminate, near_duplicates, ngram_lm, quality, repeats, secrets, sharding, url_filter
from proxcore.llm.common import read

SHARDS, SLOTS = [f"shard-{k:02d}" for k in range(16)], 2003


def op1_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, items = read(spark, sf_dir, "documents").select("doc_id", "text"), read(spark, sf_dir, "benchmark")
    found = decontaminate.scan(docs, items)
    return found.select(
        "doc_id", "hits.n_words", "hits.n_hit", F.size("hits.item_ids").cast("bigint").alias("n_items"),
        F.sha2(F.array_join("hits.item_ids", ","), 256).alias("items_sha256"), decontaminate.is_contaminated().alias("contaminated"),
    )


OP1_SQL = r"""
WITH folded AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
items AS (SELECT CAST(item_id AS VARCHAR) AS item, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark WHERE item_id IS NOT NULL AND text IS NOT NULL),
sized AS (SELECT item, w, least(13, len(w)) AS n FROM items WHERE len(w) > 0),
windows AS (SELECT DISTINCT item, n, array_to_string(list_slice(w, k, k + n - 1), ' ') AS win FROM (SELECT item, w, n, unnest(range(1, len(w) - n + 2)) AS k FROM sized)),
sizes AS (SELECT DISTINCT n FROM windows),
placed AS (SELECT doc_id, n, k, array_to_string(list_slice(w, k, k + n - 1), ' ') AS win FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS k FROM folded, sizes)),
met AS (SELECT doc_id, placed.n, k, item FROM placed JOIN windows ON placed.n = windows.n AND placed.win = windows.win),
hit AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(k, k + n)) AS p FROM met) GROUP BY doc_id),
found AS (SELECT doc_id, count(DISTINCT item) AS n_items, sha256(array_to_string(list_sort(list(DISTINCT item)), ',')) AS h FROM met GROUP BY doc_id)
SELECT f.doc_id, len(w) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, coalesce(h, sha256('')) AS items_sha256,
  coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM folded f LEFT JOIN hit ON f.doc_id = hit.doc_id LEFT JOIN found ON f.doc_id = found.doc_id
"""


def op2_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.place(read(spark, sf_dir, "documents").select("doc_id"), "doc_id", SHARDS, SLOTS).select("doc_id", "slot", "shard")


OP2_SQL = f"""
WITH RECURSIVE shards AS (SELECT 'shard-' || lpad(CAST(k AS VARCHAR), 2, '0') AS name, k FROM range({len(SHARDS)}) t(k)),
prefs AS (SELECT list(('0x' || substr(md5('offset:' || name), 1, 8))::BIGINT % {SLOTS} ORDER BY name) AS first, list(1 + ('0x' || substr(md5('skip:' || name), 1, 8))::BIGINT % {SLOTS - 1} ORDER BY name) AS skip FROM shards),
fill(turn, owner, tried) AS (
  SELECT 0, list_transform(range({SLOTS}), lambda x: -1), list_transform(range({len(SHARDS)}), lambda x: 0)
  UNION ALL
  SELECT turn + 1, list_transform(owner, lambda x, i: CASE WHEN i - 1 = (first[who] + skip[who] * best) % {SLOTS} THEN who - 1 ELSE x END), list_transform(tried, lambda x, i: CASE WHEN i = who THEN best + 1 ELSE x END)
  FROM (SELECT turn, owner, tried, first, skip, who, list_filter(range(tried[who], {SLOTS}), lambda k: owner[(first[who] + skip[who] * k) % {SLOTS} + 1] < 0)[1] AS best
        FROM (SELECT *, turn % {len(SHARDS)} + 1 AS who FROM fill, prefs WHERE turn < {SLOTS}))
),
full_table AS (SELECT unnest(range({SLOTS})) AS slot, unnest(owner) AS who FROM fill WHERE turn = {SLOTS})
SELECT doc_id, CAST(t.slot AS INTEGER) AS slot, 'shard-' || lpad(CAST(who AS VARCHAR), 2, '0') AS shard
FROM documents JOIN full_table t ON t.slot = ('0x' || substr(md5('key:' || coalesce(CAST(doc_id AS VARCHAR), '')), 1, 8))::BIGINT % {SLOTS}
"""


def op3_language_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_lm.score(read(spark, sf_dir, "documents").select("doc_id", "text"), order=3)


def op4_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source")
    return quality.score(docs, columns=["doc_id"])


def op5_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.round_trip(read(spark, sf_dir, "documents").select("doc_id", "text")).select("doc_id", "trip.n_tokens", "trip.ids_sha256", "trip.decoded_sha256")


def op6_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates.classes(read(spark, sf_dir, "documents").select("doc_id", "text"))


def op7_perspectives(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = chat.rotate(read(spark, sf_dir, "conversations"))
    return out.select("conv_id", "chunk", "speaker", "n_turns", "start", "context", "n_mask_chars", "rendered", F.concat_ws(",", F.transform("mask", lambda s: F.concat_ws("-", s["start"].cast("string"), s["end"].cast("string")))).alias("mask"))


OP7_SQL = r"""
WITH t AS (SELECT DISTINCT conv_id, CAST(floor(turn / 64) AS BIGINT) AS chunk, turn, coalesce(replace(replace(replace(replace(replace(role, '&', '&amp;'), '<', '&lt;'), '>', '&gt;'), '|', '&#124;'), chr(10), '&#10;'), '&null;') AS role, replace(coalesce(text, ''), '<|', '< |') AS text FROM conversations),
d AS (SELECT *, CASE WHEN conv_id IS NULL THEN 'turn ' || row_number() OVER () ELSE 'conversation ' || conv_id END AS dialogue FROM t),
who AS (SELECT DISTINCT dialogue, role AS speaker FROM d WHERE role <> 'system'),
seg AS (SELECT d.*, speaker, role = speaker AS own,
  CASE WHEN role = speaker THEN '<|im_start|>assistant' WHEN role = 'system' THEN '<|im_start|>system' ELSE '<|im_start|>user name=' || role END || chr(10) AS head, text || '<|im_end|>' AS body
  FROM d JOIN who ON d.dialogue = who.dialogue),
placed AS (SELECT *, CAST(coalesce(sum(length(head) + length(body) + 1) OVER (PARTITION BY dialogue, speaker ORDER BY turn NULLS FIRST, role, text ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS b FROM seg),
lead AS (SELECT dialogue, chunk, string_agg('<|im_start|>system' || chr(10) || text || '<|im_end|>' || chr(10), '' ORDER BY turn NULLS FIRST, text) FILTER (role = 'system') AS context, row_number() OVER (PARTITION BY dialogue ORDER BY chunk NULLS FIRST) AS k FROM d GROUP BY dialogue, chunk)
SELECT conv_id, p.chunk, speaker, count(*) AS n_turns, min(b) AS start, CASE WHEN p.chunk IS NOT DISTINCT FROM any_value(l.chunk) THEN '' ELSE coalesce(any_value(context), '') END AS context, CAST(coalesce(sum(CASE WHEN own THEN length(body) END), 0) AS BIGINT) AS n_mask_chars,
  string_agg(head || body || chr(10), '' ORDER BY turn NULLS FIRST, role, text) AS rendered,
  coalesce(string_agg(CASE WHEN own THEN CAST(b + length(head) AS VARCHAR) || '-' || CAST(b + length(head) + length(body) AS VARCHAR) END, ',' ORDER BY turn NULLS FIRST, role, text), '') AS mask
FROM placed p JOIN lead l ON l.dialogue = p.dialogue AND k = 1 GROUP BY conv_id, p.dialogue, p.chunk, speaker
"""


def op8_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeats.remove_repeats(read(spark, sf_dir, "documents").select("doc_id", "text"))


def op9_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents").select("doc_id", "text")
    words = secrets.vocabulary(docs)
    model = secrets.train(secrets.labelled_findings(spark), words)
    out = secrets.judge(secrets.candidates(docs, "doc_id"), model, words)
    return out.select("doc_id", "start", "end", F.sha2("value", 256).alias("value_sha256"), "probability", "is_secret")


def _hash(of: Column, salt: str) -> Column:
    return F.conv(F.substring(F.md5(F.concat(F.lit(salt), of)), 1, 8), 16, 10).cast("bigint")


def url_list(pages: DataFrame) -> DataFrame:
    """A dated list over the pages' own domains and paths, for the tables have none: a fifth of the names are added on
    a day that follows from the name, half of these are removed later, and a quarter of those come back."""
    names = pages.select(F.explode(url_filter.keys(F.col("url"))).alias("entry")).distinct().where(_hash(F.col("entry"), "listed:") % 5 == 0)
    e = F.col("entry")
    first = (_hash(e, "first:") % 300).cast("int")
    stay, gap = (1 + _hash(e, "stay:") % 90).cast("int"), (1 + _hash(e, "gap:") % 60).cast("int")
    record = lambda day, added: F.struct(F.date_add(F.lit("2024-01-01").cast("date"), day).alias("at"), F.lit(added).alias("added"))
    all_of = F.when(_hash(e, "fate:") % 8 == 0, F.array(record(first, True), record(first + stay, False), record(first + stay + gap, True))).when(_hash(e, "fate:") % 8 < 4, F.array(record(first, True), record(first + stay, False))).otherwise(F.array(record(first, True)))
    return names.select("entry", F.explode(all_of).alias("r")).select("entry", "r.at", "r.added")


def op10_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = read(spark, sf_dir, "pages").select("page_id", "url")
    fetched = F.date_add(F.lit("2024-01-01").cast("date"), (F.col("page_id") * 37 % 366).cast("int"))
    out = url_filter.evaluate(pages.withColumn("fetched_at", fetched), url_list(pages))
    return out.select("page_id", F.datediff("fetched_at", F.lit("2024-01-01").cast("date")).cast("bigint").alias("fetched_day"), "n_active", F.array_join("entries", " ").alias("entries"), "blocked")


OP10_SQL = r"""
WITH p AS (SELECT page_id, url, page_id * 37 % 366 AS day, lower(regexp_extract(url, '^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?(\[[^\]/?#]*\]|[^/:?#]+)', 1)) AS host, regexp_extract(url, '^[a-zA-Z][a-zA-Z0-9+.-]*://[^/?#]+/([^/?#]+)', 1) AS seg FROM pages),
offered AS (
  SELECT DISTINCT page_id, day, 'domain:' || array_to_string(list_slice(l, k, len(l)), '.') AS entry FROM (SELECT page_id, day, l, unnest(range(1, greatest(len(l) - 1, 1) + 1)) AS k FROM (SELECT page_id, day, CASE WHEN host LIKE '[%' THEN [host] ELSE string_split(host, '.') END AS l FROM p WHERE host <> ''))
  UNION SELECT page_id, day, 'path:' || host || '/' || seg FROM p WHERE host <> '' AND seg <> ''),
names AS (SELECT DISTINCT entry, ('0x' || substr(md5('first:' || entry), 1, 8))::BIGINT % 300 AS f, 1 + ('0x' || substr(md5('stay:' || entry), 1, 8))::BIGINT % 90 AS s, 1 + ('0x' || substr(md5('gap:' || entry), 1, 8))::BIGINT % 60 AS g, ('0x' || substr(md5('fate:' || entry), 1, 8))::BIGINT % 8 AS fate
  FROM offered WHERE ('0x' || substr(md5('listed:' || entry), 1, 8))::BIGINT % 5 = 0),
spans AS (SELECT entry, f AS since, CASE WHEN fate < 4 THEN f + s END AS until FROM names UNION ALL SELECT entry, f + s + g, NULL FROM names WHERE fate = 0),
hits AS (SELECT o.page_id, list_sort(list(DISTINCT o.entry)) AS e FROM offered o JOIN spans USING (entry) WHERE since <= day AND (until IS NULL OR day < until) GROUP BY o.page_id)
SELECT p.page_id, p.day AS fetched_day, CAST(coalesce(len(e), 0) AS BIGINT) AS n_active, coalesce(array_to_string(e, ' '), '') AS entries, coalesce(len(e), 0) > 0 AS blocked FROM p LEFT JOIN hits ON p.page_id = hits.page_id
"""

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (op1_decontaminate, op2_sharding, op3_language_model, op4_quality, op5_bpe, op6_near_duplicates, op7_perspectives, op8_repeats, op9_secrets, op10_url_filter)
}
ORACLE_SQL: dict[str, str] = {"op1_decontaminate": OP1_SQL, "op2_sharding": OP2_SQL, "op7_perspectives": OP7_SQL, "op10_url_filter": OP10_SQL}

"""URL filters by a temporal list join. A list is a history of dated entries, each added or removed on a date. Entries
become validity intervals; each capture is held, as of its own fetch time, against the entries that were active then.

An entry names a domain (with all below it) or a host's first path segment. A capture offers each of its domain
suffixes and its path key to one equi-join with a range condition; the list side is broadcast only where Spark finds it
small. Captures of a hot entry are dealt over several parts, and its few intervals repeated in each.

Defined results: a null or hostless URL matches nothing and is kept; a null fetch time matches nothing; of several
records of an entry on one date a removal wins; an entry added twice stays one interval; a removal without an addition
has no effect; repeated captures are each judged.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from proxcore.llm.common import spread_join

_HOST = r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?(\[[^\]/?#]*\]|[^/:?#]+)"
_SEGMENT = r"^[a-zA-Z][a-zA-Z0-9+.-]*://[^/?#]+/([^/?#]+)"


def host(url: Column) -> Column:
    return F.lower(F.regexp_extract(url, _HOST, 1))


def keys(url: Column) -> Column:
    """What a list may name of a URL: its domain suffixes of two labels or more, and its host with the first path segment."""
    labels = F.when(F.startswith(host(url), F.lit("[")), F.array(host(url))).otherwise(F.split(host(url), "\\."))  # an address in brackets is whole
    n = F.size(labels)
    suffixes = F.transform(F.sequence(F.lit(1), F.greatest(n - 1, F.lit(1))), lambda k: F.concat(F.lit("domain:"), F.array_join(F.slice(labels, k, n), ".")))
    segment = F.regexp_extract(url, _SEGMENT, 1)
    path = F.when(segment != "", F.array(F.concat(F.lit("path:"), host(url), F.lit("/"), segment))).otherwise(F.array().cast("array<string>"))
    return F.when(F.coalesce(host(url), F.lit("")) == "", F.array().cast("array<string>")).otherwise(F.concat(suffixes, path))


def intervals(entries: DataFrame) -> DataFrame:
    """entry, since, until (null while active) from records: entry, at (date), added (boolean)."""
    daily = entries.where("entry is not null and at is not null and added is not null").groupBy("entry", "at").agg(F.min("added").alias("added"))
    order = Window.partitionBy("entry").orderBy("at")
    changes = daily.withColumn("was", F.coalesce(F.lag("added").over(order), F.lit(False))).where(F.col("was") != F.col("added"))
    return changes.withColumn("until", F.lead("at").over(order)).where("added").select("entry", F.col("at").alias("since"), "until")


def evaluate(captures: DataFrame, entries: DataFrame, *, capture_id: str = "page_id", url: str = "url", at: str = "fetched_at") -> DataFrame:
    """capture_id, at, n_active (entries that apply), entries (their names in order), blocked: a row for each capture."""
    active = intervals(entries)
    rows = captures.select(F.col(capture_id).alias("capture_id"), F.col(at).alias("fetched"), F.col(url).alias("url"))
    offered = rows.select("capture_id", "fetched", "url", F.explode(F.array_distinct(keys(F.col("url")))).alias("entry"))
    hits = spread_join(offered, active.withColumnRenamed("entry", "__entry"), "entry", "__entry").where("since <= fetched and (until is null or fetched < until)")
    # each capture meets an entry in one interval at most; captures that are equal in all three columns have equal results
    found = hits.groupBy(F.col("capture_id").alias("c"), F.col("fetched").alias("f"), F.col("url").alias("u")).agg(F.array_sort(F.collect_set("entry")).alias("found"))
    same = F.col("capture_id").eqNullSafe(F.col("c")) & F.col("fetched").eqNullSafe(F.col("f")) & F.col("url").eqNullSafe(F.col("u"))
    out = rows.join(found, same, "left").withColumn("entries", F.coalesce("found", F.array().cast("array<string>")))
    return out.select(F.col("capture_id").alias(capture_id), F.col("fetched").alias(at), F.size("entries").cast("bigint").alias("n_active"), "entries", (F.size("entries") > 0).alias("blocked"))

"""Events as a stream of files: edges, bursts, states of vertices and continuous queries.

Scores can't be kept by one forward pass, for a state's normaliser depends on later arcs. So the stream keeps edges and
per-vertex last times, and registered queries are worked out anew on what each batch has changed.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from proxcore.exact import exact_community
from proxcore.graph import SlotGraph
from proxcore.runtime import shared_dir
from proxcore.sources.tables import SCHEMAS


def source(spark: SparkSession, folder: str, files: int = 1) -> DataFrame:
    """Event files as they come; ts as an instant."""
    rows = spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", files).parquet(folder)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def once(events: DataFrame, delay: str = "2 hours") -> DataFrame:
    """Each event once, within the watermark; later repeats and late rows are dropped."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def meetings(events: DataFrame, seconds: int = 600, delay: str = "1 hour") -> DataFrame:
    """u, v, t: users with a purchase in the same slot; a stream joined to itself within the slot, both under a watermark. The state has
    every purchase twice, and a pair may come again; `gatherings` keeps each slot's users instead."""
    buys = events.where("event_type = 'purchase'").withWatermark("ts", delay)
    slot = F.floor(F.unix_timestamp("ts") / seconds)
    a = buys.select(F.col("user_id").alias("u"), slot.alias("t"), F.col("ts").alias("at"))
    b = buys.select(F.col("user_id").alias("v"), slot.alias("s"), F.col("ts").alias("bt"))
    near = F.expr(f"u < v and t = s and bt >= at - interval {seconds} seconds and bt <= at + interval {seconds} seconds")
    return a.join(b, near).select("u", "v", "t", F.greatest("at", "bt").alias("ts"))


def gatherings(events: DataFrame, seconds: int = 600, delay: str = "1 hour") -> DataFrame:
    """t, old, fresh: the users (arrays) whose first purchase in a slot a batch has, and those that came before them. A slot's users are its
    state, which goes when the watermark has passed the slot. `pairs` makes the meetings of it, each once."""

    def run(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        old = list(state.get[0]) if state.exists else []
        fresh = sorted({int(x) for part in parts for x in part["user_id"]}.difference(old))
        state.update(([*old, *fresh],))
        state.setTimeoutTimestamp(max((int(key[0]) + 1) * seconds * 1000, state.getCurrentWatermarkMs() + 1))
        if fresh:
            yield pd.DataFrame({"t": [key[0]], "old": [old], "fresh": [fresh]})

    buys = events.where("event_type = 'purchase' and ts is not null and user_id is not null").withWatermark("ts", delay)
    slot = buys.select("user_id", "ts", F.floor(F.unix_timestamp("ts") / seconds).alias("t"))
    return slot.groupBy("t").applyInPandasWithState(run, "t bigint, old array<bigint>, fresh array<bigint>", "members array<bigint>", "append", GroupStateTimeout.EventTimeTimeout)


def pairs(slots: DataFrame) -> DataFrame:
    """u, v, t of gatherings: each fresh user with the old ones and with the fresh ones after it."""
    one = slots.select("t", "old", "fresh", F.posexplode("fresh").alias("k", "a"))
    both = one.select("t", "a", F.explode(F.concat("old", F.slice("fresh", F.col("k") + 2, F.size("fresh")))).alias("b"))
    return both.select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v"), "t")


def hourly(events: DataFrame, delay: str = "2 hours", slide: str | None = None) -> DataFrame:
    """start, event_type, n, total by tumbling or sliding hours."""
    span = F.window("ts", "1 hour", slide) if slide else F.window("ts", "1 hour")
    return events.withWatermark("ts", delay).groupBy(span.alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", "total")


def bursts(events: DataFrame, gap: str = "30 minutes", delay: str = "2 hours") -> DataFrame:
    """user_id, start, end, n: sessions."""
    return events.withWatermark("ts", delay).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def last_seen(events: DataFrame, delay: str = "2 hours") -> DataFrame:
    """user_id, n, last: each user's count of distinct slots and last one so far, as state that outlives batches: the frontier of
    dangling states."""

    def run(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, last = state.get if state.exists else (0, -1)
        slots = sorted({int(x) for part in parts for x in part["slot"]})
        fresh = [x for x in slots if x > last]  # an earlier slot than the last was counted or is late
        n, last = n + len(fresh), max([last, *slots])
        state.update((n, last))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "last": [last]})

    slot = events.withWatermark("ts", delay).select("user_id", F.floor(F.unix_timestamp("ts") / 3600).alias("slot"))
    return slot.groupBy("user_id").applyInPandasWithState(run, "user_id bigint, n bigint, last bigint", "n bigint, last bigint", "update", GroupStateTimeout.NoTimeout)


def drain(df: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """All that is available, as a table of Parquet files in the folder that the cluster shares: the rows of all batches, or in
    complete mode those of the last one. No row passes the driver; a batch that runs again replaces its own rows."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/stream-{name}-{uuid.uuid4().hex}"
    spark.createDataFrame([], df.schema).write.parquet(f"{path}/batch=none")

    def batch(rows: DataFrame, number: int) -> None:
        rows.write.mode("overwrite").parquet(f"{path}/batch={'all' if mode == 'complete' else number}")

    writer = df.writeStream.queryName(name).outputMode(mode).trigger(availableNow=True).foreachBatch(batch)
    (writer.option("checkpointLocation", checkpoint) if checkpoint else writer).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{path}/batch=*")


def land(df: DataFrame, path: str, checkpoint: str) -> None:
    """All that is available, appended to Parquet files; a later call goes on where the checkpoint ends."""
    df.writeStream.format("parquet").option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start(path).awaitTermination()


def follow(events: DataFrame, queries: Iterable[int], store: str, checkpoint: str, sink: Callable[[DataFrame, int], None], *, seconds: int = 600) -> StreamingQuery:
    """A continuous query: each batch is added to the store (once, by batch number), and the registered queries' communities are
    found anew over the edges of all batches and given to the sink."""
    wanted = sorted(set(queries))

    def batch(df: DataFrame, number: int) -> None:
        df.where("event_type = 'purchase'").select("user_id", F.floor(F.unix_timestamp("ts") / seconds).alias("t")).distinct().write.mode("overwrite").parquet(f"{store}/batch={number}")
        slots = df.sparkSession.read.parquet(store).select("user_id", "t").distinct()
        sink(exact_community(SlotGraph(slots.select(F.col("user_id").alias("v"), "t")).settled(), wanted), number)

    return events.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()

"""Edge lists in text, CSV, JSON and Parquet, sinks, and the partitioned and bucketed store of a graph."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from proxcore.graph import TemporalGraph

EDGE = "u bigint, v bigint, t bigint"


def read_edges(spark: SparkSession, path: str, kind: str = "text") -> TemporalGraph:
    """kind: text (u v t by white space, # comments), csv, json, parquet or orc. Lines that aren't three numbers are dropped."""
    if kind == "text":
        parts = F.split(F.trim("value"), r"\s+")
        rows = spark.read.text(path).where("value not like '#%'").select(*[F.get(parts, F.lit(k)).try_cast("bigint").alias(c) for k, c in enumerate("uvt")])
    elif kind == "csv":
        rows = spark.read.csv(path, schema=EDGE, header=True)
    elif kind == "json":
        rows = spark.read.json(path, schema=EDGE)
    else:
        rows = spark.read.format(kind).schema(EDGE).load(path)
    return TemporalGraph.from_edges(rows.where("u is not null and v is not null and t is not null"))


def write_edges(g: TemporalGraph, path: str, kind: str = "parquet") -> None:
    """kind: parquet, orc, csv, json, text or noop (which only works the edges out)."""
    if kind == "noop":
        g.edges.write.format("noop").mode("overwrite").save()
    elif kind == "text":
        g.edges.select(F.concat_ws(" ", "u", "v", "t")).write.text(path)
    else:
        g.edges.write.format(kind).option("header", "true").save(path)


def store(g: TemporalGraph, path: str, slab: int) -> None:
    """Edges partitioned by slab of time, so that slices and passes by slab read what they need."""
    g.edges.withColumn("slab", F.floor(F.col("t") / slab)).repartition("slab").sortWithinPartitions("t", "u").write.partitionBy("slab").parquet(path)


def open_store(spark: SparkSession, path: str, slab: int, since: int | None = None, until: int | None = None) -> TemporalGraph:
    """The stored graph, cut to since <= t < until by whole slabs before any file is opened."""
    rows = spark.read.schema(f"{EDGE}, slab bigint").parquet(path)
    rows = rows if since is None else rows.where((F.col("slab") >= since // slab) & (F.col("t") >= since))
    rows = rows if until is None else rows.where((F.col("slab") <= (until - 1) // slab) & (F.col("t") < until))
    return TemporalGraph(rows.select("u", "v", "t"))


def store_arcs(g: TemporalGraph, name: str, buckets: int, path: str | None = None) -> None:
    """Arcs as a table bucketed by source, in the warehouse or at a path: joins on src need no shuffle of it, and a lookup reads
    one bucket."""
    writer = g.arcs.repartition(buckets, "src").write.bucketBy(buckets, "src").sortBy("src", "t").mode("overwrite")
    (writer if path is None else writer.option("path", path)).saveAsTable(name)


def arcs_of(spark: SparkSession, name: str, sources: DataFrame) -> DataFrame:
    """The arcs of some sources (first column) from a bucketed table."""
    return spark.table(name).join(sources.select(F.col(sources.columns[0]).alias("src")).distinct(), "src", "left_semi")

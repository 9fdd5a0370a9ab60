"""What the corpus operators share: reading tables, cutting lineage and Arrow row functions."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_type


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


_own: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder that the cluster shares, from spark.checkpoint.dir; a folder of this machine where that is unset."""
    if found := spark.conf.get("spark.checkpoint.dir", None):
        return found
    app = spark.sparkContext.applicationId
    if app not in _own:
        _own[app] = tempfile.mkdtemp(prefix="corpus_")
    return _own[app]


def keep(df: DataFrame) -> DataFrame:
    """Writes df to the shared folder as Parquet and reads it back: cuts the lineage and survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/kept-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def hot_keys(df: DataFrame, key: str, share: int = 4) -> DataFrame:
    """key, salts for keys that hold over 1 / (share * partitions) of the rows, so at most share * partitions of them: small
    enough to broadcast at any size. salts says over how many parts such a key's rows should be dealt."""
    n = partitions(df.sparkSession)
    sizes = keep(df.where(F.col(key).isNotNull()).groupBy(key).agg(F.count("*").alias("n")))
    total = sizes.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("total"))
    bound = F.greatest(F.lit(64.0), F.col("total") / (share * n))
    return sizes.crossJoin(F.broadcast(total)).where(F.col("n") > bound).select(key, F.ceil(F.col("n") / bound).cast("int").alias("salts"))  # a single row


def spread_join(left: DataFrame, right: DataFrame, key: str, other: str, how: str = "inner") -> DataFrame:
    """left joined with right on left.key = right.other; the rows of hot left keys are dealt over several parts, and right rows of
    these keys repeated as often. Neither side may have the columns __salt or __salts."""
    by = [F.col(c) for c, kind in left.dtypes if "map<" not in kind]  # salts follow from rows and parts, so a task that runs again deals alike
    hot = keep(hot_keys(left, key)).withColumnsRenamed({key: "__hot", "salts": "__salts"})
    a = left.join(F.broadcast(hot), F.col(key) == F.col("__hot"), "left")
    a = a.withColumn("__salt", F.when(F.col("__salts").isNull(), 0).otherwise(F.pmod(F.xxhash64(*by) + F.spark_partition_id(), F.col("__salts")).cast("int"))).drop("__hot", "__salts")
    b = right.join(F.broadcast(hot), F.col(other) == F.col("__hot"), "left")
    b = b.withColumn("__of", F.explode(F.sequence(F.lit(0), F.coalesce(F.col("__salts"), F.lit(1)) - 1))).drop("__hot", "__salts")
    return a.join(b, (F.col(key) == F.col(other)) & (F.col("__salt") == F.col("__of")), how).drop("__salt", "__of")


def with_struct(df: DataFrame, text: str, out: str, kind: T.StructType, make: Callable[[Iterator[str | None]], list[dict]]) -> DataFrame:
    """Appends the struct column `out`, which make() derives from a batch's texts; a column of that name is replaced.
    All else passes through, so repeated rows, null ids and extra columns stay as they are."""
    df = df.drop(out)
    at = df.columns.index(text)
    arrow = to_arrow_type(kind)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for low in range(0, batch.num_rows, 512):
                part = batch.slice(low, 512)
                made = pa.array(make(x.as_py() for x in part.column(at)), arrow)
                yield pa.RecordBatch.from_arrays([*part.columns, made], [*part.schema.names, out])

    return df.mapInArrow(run, T.StructType([*df.schema.fields, T.StructField(out, kind)]))

"""Cutting lineage in iterative plans: each settled table is written to the folder that the cluster shares."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_paths: list[str] = []
_own: dict[str, str] = {}
_caches: list[Callable[[], None]] = []


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session; a folder of this machine only where that is unset."""
    if found := spark.conf.get("spark.checkpoint.dir", None):
        return found
    app = spark.sparkContext.applicationId
    if app not in _own:
        _own[app] = tempfile.mkdtemp(prefix="proxcore_")
    return _own[app]


def settle(df: DataFrame) -> DataFrame:
    """df as a table of its own: survives lost executors, has a known size, and ends the plan above it."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/settled-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _paths.append(path)
    return spark.read.schema(df.schema).parquet(path)


class Growing:
    """A table that rounds add to. Each part is written once; only every MERGE-th one rewrites the whole."""

    MERGE = 8

    def __init__(self, first: DataFrame):
        self._parts = [settle(first)]

    def add(self, df: DataFrame) -> DataFrame:
        """The part that was added, as a table."""
        part = settle(df)
        self._parts.append(part)
        if len(self._parts) > self.MERGE:
            self._parts = [settle(self.table)]
        return part

    @property
    def table(self) -> DataFrame:
        out = self._parts[0]
        for part in self._parts[1:]:
            out = out.unionByName(part)
        return out


def forget_at_sweep(forget: Callable[[], None]) -> None:
    """Registers what drops a cache of settled tables."""
    _caches.append(forget)


def sweep(spark: SparkSession) -> int:
    """Deletes what settle() has written so far; call it once results are stored elsewhere."""
    for forget in _caches:
        forget()
    n = 0
    while _paths:
        path = spark._jvm.org.apache.hadoop.fs.Path(_paths.pop())
        n += bool(path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True))
    return n


def query_table(spark: SparkSession, queries: DataFrame | Iterable[int]) -> DataFrame:
    """q: distinct query vertices."""
    if isinstance(queries, DataFrame):
        return queries.select(F.col(queries.columns[0]).cast("bigint").alias("q")).distinct()
    return spark.createDataFrame([(int(q),) for q in sorted(set(queries))], "q bigint")

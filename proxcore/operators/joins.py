"""As-of, interval and range joins as compositions of equi-joins and windows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof(left: DataFrame, right: DataFrame, by: str, at: str, take: list[str], *, strict: bool = False) -> DataFrame:
    """left with the columns `take` of the latest right row of the same key at or before (strictly before, if strict) its
    time; nulls without one. One union and one window by key, so the sides never multiply."""
    rest = [c for c in left.columns if c not in (by, at)]
    a = left.select(F.col(by).alias("__k"), F.col(at).alias("__t"), F.lit(0 if strict else 1).alias("__o"), F.struct(*rest).alias("__l") if rest else F.struct(F.lit(0)).alias("__l"), F.lit(None).alias("__r"))
    b = right.select(F.col(by).alias("__k"), F.col(at).alias("__t"), F.lit(1 if strict else 0).alias("__o"), F.lit(None).alias("__l"), F.struct(*take).alias("__r"))
    run = Window.partitionBy("__k").orderBy("__t", "__o").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b).withColumn("__last", F.last("__r", ignorenulls=True).over(run)).where("__l is not null")
    return both.select(F.col("__k").alias(by), F.col("__t").alias(at), *[F.col(f"__l.{c}").alias(c) for c in rest], *[F.col(f"__last.{c}").alias(c) for c in take])


def within(left: DataFrame, right: DataFrame, at: str, other_at: str, delta: int) -> DataFrame:
    """Pairs whose whole-number times differ by at most delta: an equi-join on buckets of delta, of which the right side has
    three, so that a bucket's rows meet and nothing is compared across."""
    width = max(1, delta)
    a = left.withColumn("__b", F.floor(F.col(at) / width))
    b = right.withColumn("__b", F.explode(F.array(*[F.floor(F.col(other_at) / width) + k for k in (-1, 0, 1)])))
    return a.join(b, "__b").where(F.abs(F.col(at) - F.col(other_at)) <= delta).drop("__b")


def salted(left: DataFrame, right: DataFrame, on: list[str], salts: int = 16, how: str = "inner") -> DataFrame:
    """An equi-join whose hot left keys are spread over `salts` parts; the right side is repeated as often. For left skew that
    adaptive execution can't split, as below an aggregation on the key."""
    a = left.withColumn("__salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)))
    b = right.withColumn("__salt", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(salts - 1).cast("bigint"))))
    return a.join(b, [*on, "__salt"], how).drop("__salt")


def top_per_group(df: DataFrame, by: list[str], order: list[Column], k: int) -> DataFrame:
    """The first k rows of each group; Spark cuts each task's groups before the shuffle."""
    return df.withColumn("__r", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col("__r") <= k).drop("__r")


def runs(df: DataFrame, by: list[str], at: str, gap: int = 1) -> DataFrame:
    """Keys with first, last, n of each run of times that follow one another within `gap`."""
    own = Window.partitionBy(*by).orderBy(at)
    marked = df.withColumn("__new", F.coalesce((F.col(at) - F.lag(at).over(own) > gap).cast("int"), F.lit(1)))
    return marked.withColumn("__run", F.sum("__new").over(own)).groupBy(*by, "__run").agg(F.min(at).alias("first"), F.max(at).alias("last"), F.count("*").alias("n")).drop("__run")

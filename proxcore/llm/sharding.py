"""Sharding by a permutation-filled lookup table. Each shard has a preference order of the slots, an arithmetic
progression modulo the prime number of slots; shards take turns and claim their best free slot until the table is full.
A key's slot is its hash modulo the size, its shard what the table holds there: one look-up in a broadcast table.

The table is filled by one SQL expression over the list of shards and depends on their names alone. Shares differ by at
most one slot; removing a shard moves its own keys and few others.

Defined results: a null key counts as the empty string; equal keys go together; repeated shard names count once; without
shards, or with a size that isn't a prime above their number, a ValueError is raised.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Slots that a table may have: it is broadcast and filled in a time that grows with the square.
MOST_SLOTS = 8191


def _number(of: Column, salt: str) -> Column:
    """32 bits of a hash that any SQL engine has."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(salt), of)), 1, 8), 16, 10).cast("bigint")


def _is_prime(n: int) -> bool:
    return n > 1 and all(n % k for k in range(2, int(n**0.5) + 1))


def lookup_table(spark: SparkSession, shards: Sequence[str], slots: int = 2003) -> DataFrame:
    """slot, shard: one row for each slot."""
    names = sorted(set(shards))
    if not names or not _is_prime(slots) or not len(names) < slots <= MOST_SLOTS:
        raise ValueError(f"needs shards and a prime number of slots above theirs, up to {MOST_SLOTS}")
    n = len(names)
    name = F.array(*map(F.lit, names))
    order = F.struct(F.transform(name, lambda x: _number(x, "offset:") % slots).alias("first"), F.transform(name, lambda x: 1 + _number(x, "skip:") % (slots - 1)).alias("skip"))

    def claim(order: Column, state: Column, turn: Column) -> Column:
        who = (turn % n).cast("int")
        slot = lambda k: ((F.get(order["first"], who) + F.get(order["skip"], who) * k) % slots).cast("int")
        best = F.get(F.filter(F.sequence(F.get(state["tried"], who), F.lit(slots - 1)), lambda k: F.get(state["owner"], slot(k)) < 0), F.lit(0))

        def take(b: Column) -> Column:
            return F.struct(
                F.transform(state["owner"], lambda x, k: F.when(k == b["slot"], b["who"]).otherwise(x)).alias("owner"),
                F.transform(state["tried"], lambda x, k: F.when(k == b["who"], b["next"]).otherwise(x)).alias("tried"),
            )

        # an array of one, so that the choice is made once and not for each slot
        bound = F.transform(F.array(best), lambda b: F.struct(slot(b).alias("slot"), who.alias("who"), (b + 1).alias("next")))
        return F.get(F.transform(bound, take), F.lit(0))

    empty = F.struct(F.array_repeat(F.lit(-1), slots).alias("owner"), F.array_repeat(F.lit(0), n).alias("tried"))
    # the orders are bound once, by an array of one, and not worked out anew for each look
    fill = F.transform(F.array(order), lambda o: F.aggregate(F.sequence(F.lit(0), F.lit(slots - 1)), empty, lambda s, turn: claim(o, s, turn), lambda s: s["owner"]))
    return spark.range(1).select(F.posexplode(F.get(fill, F.lit(0))).alias("slot", "who")).select("slot", F.get(name, F.col("who")).alias("shard"))


def slot_of(key: Column, slots: int = 2003) -> Column:
    return (_number(F.coalesce(key.cast("string"), F.lit("")), "key:") % slots).cast("int")


def place(df: DataFrame, key: str, shards: Sequence[str], slots: int = 2003, *, out: str = "shard", slot: str = "slot") -> DataFrame:
    """df with its slot and shard; columns of these names are replaced. No shuffle: the table of at most MOST_SLOTS rows is broadcast."""
    table = lookup_table(df.sparkSession, shards, slots).select(F.col("slot").alias("__slot"), F.col("shard").alias("__shard"))
    rest = df.withColumn("__key_slot", slot_of(F.col(key), slots)).drop(out, slot) if key not in (out, slot) else df.withColumn("__key_slot", slot_of(F.col(key), slots))
    return rest.join(F.broadcast(table), F.col("__key_slot") == F.col("__slot")).withColumn(slot, F.col("__slot")).withColumn(out, F.col("__shard")).drop("__slot", "__shard", "__key_slot")


def moved(spark: SparkSession, before: Sequence[str], after: Sequence[str], slots: int = 2003) -> DataFrame:
    """Slots that change hands between two lists of shards, by old and new shard."""
    old, new = lookup_table(spark, before, slots), lookup_table(spark, after, slots).withColumnRenamed("shard", "to")
    return old.join(new, "slot").where(F.col("shard") != F.col("to")).groupBy("shard", "to").agg(F.count("*").alias("n_slots"))


def write_shards(df: DataFrame, key: str, shards: Sequence[str], path: str, slots: int = 2003) -> None:
    """One folder for each shard; a shard's rows stay spread over the tasks that read them."""
    place(df, key, shards, slots).write.partitionBy("shard").parquet(path)

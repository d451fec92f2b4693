"""Which shards see, store and count an event."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import shard_of


def hashed(events: DataFrame, n_shards: int, seed: int = 42) -> DataFrame:
    return events.withColumns({"h_u": shard_of(F.col("u"), n_shards, seed), "h_v": shard_of(F.col("v"), n_shards, seed)})


def route_count(events: DataFrame, n_shards: int, seed: int = 42) -> DataFrame:
    """The layout's messages: one to the common shard, or one to each shard. Only the reference path needs them."""
    rows = hashed(events, n_shards, seed)
    return rows.withColumn("shard", F.explode(F.when(F.col("h_u") == F.col("h_v"), F.array("h_u")).otherwise(F.sequence(F.lit(0), F.lit(n_shards - 1)))))


def route_store(events: DataFrame, n_shards: int, seed: int = 42) -> DataFrame:
    """At most two copies of an event: at the shards of its ends, which alone may store it."""
    rows = hashed(events, n_shards, seed)
    return rows.withColumn("shard", F.explode(F.array_distinct(F.array("h_u", "h_v"))))


def counting_shard(h_u: Column, h_v: Column, h_c: Column) -> Column:
    """The only shard that may count the triangle which (u, v) closes with apex c: it alone can hold both other edges."""
    return F.when(h_u == h_v, h_u).otherwise(h_c)


def message_cost(events: DataFrame, n_shards: int, seed: int = 42) -> DataFrame:
    """(shard, sent, stored): messages to each shard by the layout, and copies that the storing rule makes."""
    rows = hashed(events, n_shards, seed)
    same = F.col("h_u") == F.col("h_v")
    totals = rows.agg(F.sum((~same).cast("long")).alias("mixed"))
    own = rows.where(same).groupBy(F.col("h_u").alias("shard")).agg(F.count(F.lit(1)).alias("own"))
    stored = route_store(events, n_shards, seed).groupBy("shard").agg(F.count(F.lit(1)).alias("stored"))
    shards = events.sparkSession.range(n_shards).select(F.col("id").cast("int").alias("shard"))
    joined = shards.join(own, "shard", "left").join(stored, "shard", "left").join(F.broadcast(totals), F.lit(True))
    return joined.select("shard", (F.coalesce("own", F.lit(0)) + F.coalesce("mixed", F.lit(0))).alias("sent"), F.coalesce("stored", F.lit(0)).alias("stored"))

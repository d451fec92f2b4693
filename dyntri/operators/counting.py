"""Counting as a join of events with the sample's residency intervals."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import shard_of
from .routing import counting_shard, hashed
from .streams import BUCKET


def closing_hits(events: DataFrame, residency: DataFrame, n_shards: int, seed: int = 42) -> DataFrame:
    """(run, shard, seq, sign, u, v, c, seg_a, seg_b): every triangle that an event closes with two resident edges.

    The sample is taken as before the event: entered earlier, and not pushed out earlier. Equality on vertices and
    shard, intervals as residual conditions; the counting rule leaves each triangle to one shard. An event meets the
    resident edges of its end with fewer of them, so a vertex with very many is not multiplied by its own events.
    """
    sides = residency.select("run", "shard", "segment", F.col("u").alias("x"), F.col("v").alias("y"), "enter_seq", "exit_seq")
    both = sides.unionByName(sides.select("run", "shard", "segment", F.col("y").alias("x"), F.col("x").alias("y"), "enter_seq", "exit_seq"))
    h_c = shard_of(F.col("y"), n_shards, seed).alias("h_c")
    a = both.select("run", "shard", F.col("x").alias("near"), F.col("y").alias("c"), F.col("segment").alias("seg_near"), F.col("enter_seq").alias("in_a"), F.col("exit_seq").alias("out_a"), h_c)
    b = both.select("run", "shard", F.col("x").alias("far"), F.col("y").alias("c"), F.col("segment").alias("seg_far"), F.col("enter_seq").alias("in_b"), F.col("exit_seq").alias("out_b"))

    def there(i: str, o: str) -> Column:
        return (F.col(i) < F.col("seq")) & (F.col(o).isNull() | (F.col(o) >= F.col("seq")))

    # an event with an end that never has a resident edge closes nothing
    held = both.groupBy("x").agg(F.count(F.lit(1)).alias("n"))
    rows = events.select("seq", "u", "v", "sign").join(held.select(F.col("x").alias("u"), F.col("n").alias("n_u")), "u").join(held.select(F.col("x").alias("v"), F.col("n").alias("n_v")), "v")
    swap = F.col("n_v") < F.col("n_u")
    rows = hashed(rows, n_shards, seed).select("seq", "sign", swap.alias("swap"), F.when(swap, F.col("v")).otherwise(F.col("u")).alias("near"), F.when(swap, F.col("u")).otherwise(F.col("v")).alias("far"), "h_u", "h_v")
    # the counting rule needs the apex only, so copies held by other shards go before the second shuffle
    own = counting_shard(F.col("h_u"), F.col("h_v"), F.col("h_c"))
    first = rows.join(a, "near").where(there("in_a", "out_a") & (F.col("shard") == own)).select("run", "shard", "seq", "sign", "swap", "near", "far", "c", "seg_near")
    met = first.join(b, ["run", "shard", "far", "c"]).where(there("in_b", "out_b"))
    ends = [F.when(F.col("swap"), F.col(y)).otherwise(F.col(x)).alias(name) for x, y, name in (("near", "far", "u"), ("far", "near", "v"))]
    segments = [F.when(F.col("swap"), F.col(y)).otherwise(F.col(x)).alias(name) for x, y, name in (("seg_near", "seg_far", "seg_a"), ("seg_far", "seg_near", "seg_b"))]
    return met.select("run", "shard", "seq", "sign", *ends, "c", *segments)


def placed(closed: DataFrame, n_shards: int, seed: int = 42) -> DataFrame:
    """:func:`exact.closings` with the one shard that may count each."""
    h_u, h_v, h_c = (shard_of(F.col(x), n_shards, seed) for x in ("u", "v", "c"))
    return closed.withColumn("shard", counting_shard(h_u, h_v, h_c))


def resident_hits(closed: DataFrame, held: DataFrame) -> DataFrame:
    """:func:`closing_hits` of a stream whose closings are known: those with both edges in the sample.

    closed: shard, id_a, id_b and any further columns, which stay; held: run, shard, segment, id, exit_seq, an id once a run and shard.
    The two edges are looked up in one pass over the sample, and meet again by closing and run.
    """
    keep = [c for c in closed.columns if c not in ("id_a", "id_b")]
    sides = F.explode(F.array(F.struct(F.lit(True).alias("first"), F.col("id_a").alias("id")), F.struct(F.lit(False).alias("first"), F.col("id_b").alias("id")))).alias("side")
    rows = closed.select(*keep, sides).select(*keep, "side.first", "side.id")
    met = held.select("run", "shard", "segment", "id", "exit_seq").join(rows, ["shard", "id"]).where("exit_seq is null or exit_seq >= seq")
    segment = lambda on, name: F.max(F.when(on, F.col("segment"))).alias(name)
    both = met.groupBy("run", *keep).agg(F.count(F.lit(1)).alias("_n"), segment(F.col("first"), "seg_a"), segment(~F.col("first"), "seg_b"))
    return both.where("_n = 2").drop("_n")


def as_of(hits: DataFrame, steps: DataFrame, value: str) -> DataFrame:
    """hits with ``value`` of the last step of their shard that came strictly earlier (0 if none did).

    steps: shard, seq, value. A union and a last-value window over distinct hit places only, in buckets of seq; only a
    row per bucket meets in the window that carries the last value on.
    """
    places = hits.select("shard", "seq").distinct().select("shard", "seq", F.lit(0).alias("_step"), F.lit(None).cast("long").alias(value))
    all_ = places.unionByName(steps.select("shard", "seq", F.lit(1).alias("_step"), F.col(value).cast("long").alias(value))).withColumn("_bucket", F.floor(F.col("seq") / BUCKET))
    ends = all_.groupBy("shard", "_bucket").agg(F.max(F.when(F.col("_step") == 1, F.struct("seq", value)))[value].alias("_end"))
    earlier = Window.partitionBy("shard").orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    ends = ends.select("shard", "_bucket", F.last("_end", ignorenulls=True).over(earlier).alias("_carried"))
    before = Window.partitionBy("shard", "_bucket").orderBy("seq", "_step").rowsBetween(Window.unboundedPreceding, 0)
    known = all_.withColumn("_last", F.last(value, ignorenulls=True).over(before)).where("_step = 0").join(ends, ["shard", "_bucket"])
    return hits.join(known.select("shard", "seq", F.coalesce("_last", "_carried", F.lit(0)).alias(value)), ["shard", "seq"])


def global_estimate(hits: DataFrame, den: float, runs: int) -> DataFrame:
    """(run, est): the collector's sum over shards; runs without a hit have 0."""
    sums = hits.groupBy("run").agg(F.sum(F.col("num") * F.col("sign")).alias("num"))
    every = hits.sparkSession.range(runs).select(F.col("id").cast("int").alias("run"))
    return every.join(sums, "run", "left").select("run", F.coalesce(F.col("num").cast("double") / F.lit(float(den)), F.lit(0.0)).alias("est"))


def local_estimate(hits: DataFrame, den: float) -> DataFrame:
    """(run, node, est) of vertices with a hit; all three vertices of a triangle are credited."""
    nodes = hits.select("run", F.explode(F.array("u", "v", "c")).alias("node"), (F.col("num") * F.col("sign")).alias("num"))
    return nodes.groupBy("run", "node").agg(F.sum("num").alias("num")).select("run", "node", (F.col("num").cast("double") / F.lit(float(den))).alias("est"))


def trajectory(hits: DataFrame, den: float, every: int = 1) -> DataFrame:
    """(run, seq, est) after each ``every`` events in which something was counted: bucket sums, then sums of buckets."""
    from .streams import number_within

    at = (F.floor(F.col("seq") / every) * every).cast("long")
    steps = hits.groupBy("run", at.alias("seq")).agg(F.sum(F.col("num") * F.col("sign")).cast("double").alias("num"))
    return number_within(steps, ["run"], "seq", "total", F.col("num")).select("run", "seq", (F.col("total") / F.lit(float(den))).alias("est"))

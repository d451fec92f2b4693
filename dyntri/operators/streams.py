"""Edge streams: canonical form, order, numbering, signs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import _number
from ..sources.shared import cut

#: Rows of a stream in one bucket of a two-step running number.
BUCKET = 1 << 16


def canonical_edges(pairs: DataFrame, order: list[str]) -> DataFrame:
    """(u, v, *order): each undirected edge once, u < v, at its first occurrence; self-loops and nulls go."""
    ends = pairs.where("a is not null and b is not null and a <> b").select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v"), *order)
    return ends.groupBy("u", "v").agg(*[F.min(c).alias(c) for c in order])


def numbered(edges: DataFrame, order: list[Column | str], name: str = "seq") -> DataFrame:
    """Adds dense numbers from 0 in the given total order, without a window over all rows.

    Ranges of the order are partitions; each counts its rows, and the counts before it are added. One row per
    partition meets in a window.
    """
    spark = edges.sparkSession
    n = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 1)
    placed = cut(edges.repartitionByRange(n, *order).sortWithinPartitions(*order).withColumn("_id", F.monotonically_increasing_id()))
    part = F.shiftright("_id", 33)
    sizes = placed.groupBy(part.alias("_part")).agg(F.count(F.lit(1)).alias("_n"), F.min("_id").alias("_first"))
    before = F.coalesce(F.sum("_n").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    sizes = sizes.select("_part", "_first", before.alias("_before"))
    return placed.join(F.broadcast(sizes), part == F.col("_part")).withColumn(name, F.col("_before") + F.col("_id") - F.col("_first")).drop("_id", "_part", "_first", "_before")


def stream(edges: DataFrame, order: list[str]) -> DataFrame:
    """An insertion stream (seq, ts, u, v, sign) from canonical edges, ordered by ``order`` and then by the edge."""
    ts = F.col("ts").cast("timestamp") if "ts" in edges.columns else F.lit(None).cast("timestamp")
    rows = numbered(edges, [*order, "u", "v"])
    return rows.select("seq", ts.alias("ts"), F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v"), F.lit(1).cast("byte").alias("sign"))


def running(df: DataFrame, keys: list[str], order: str, sums: dict[str, Column], lows: dict[str, Column] | None = None) -> DataFrame:
    """Adds running sums up to each row, and minima over strictly earlier rows (null at a key's first), within keys by ``order``.

    Rows meet in buckets of the order's range; only a row per bucket meets in the window that carries them on.
    """
    lows = lows or {}
    held = df.withColumns({"_bucket": F.floor(F.col(order) / BUCKET), **{f"_v_{n}": v for n, v in {**sums, **lows}.items()}})
    ends = held.groupBy(*keys, "_bucket").agg(*[F.sum(f"_v_{n}").alias(f"_e_{n}") for n in sums], *[F.min(f"_v_{n}").alias(f"_e_{n}") for n in lows])
    before = Window.partitionBy(*keys).orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    carried = [F.coalesce(F.sum(f"_e_{n}").over(before), F.lit(0)).alias(f"_c_{n}") for n in sums] + [F.min(f"_e_{n}").over(before).alias(f"_c_{n}") for n in lows]
    inside = Window.partitionBy(*keys, "_bucket").orderBy(order).rowsBetween(Window.unboundedPreceding, 0)
    earlier = Window.partitionBy(*keys, "_bucket").orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    rows = held.withColumns({**{f"_i_{n}": F.sum(f"_v_{n}").over(inside) for n in sums}, **{f"_i_{n}": F.min(f"_v_{n}").over(earlier) for n in lows}})
    rows = rows.join(ends.select(*keys, "_bucket", *carried), [*keys, "_bucket"])
    rows = rows.withColumns({**{n: F.col(f"_i_{n}") + F.col(f"_c_{n}") for n in sums}, **{n: F.least(f"_i_{n}", f"_c_{n}") for n in lows}})
    return rows.drop("_bucket", *[f"_{x}_{n}" for x in "vic" for n in {**sums, **lows}])


def number_within(df: DataFrame, keys: list[str], order: str, name: str, value: Column | None = None) -> DataFrame:
    """Adds the running sum of ``value`` (1: a number from 1) within keys by ``order``."""
    return running(df, keys, order, {name: F.lit(1) if value is None else value})


def validated(signed: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(events, quarantine): events that insert an absent edge or delete a live one, ends in order; the rest as it came.

    Rows that are no event (a sign other than 1 and -1, a null, a self-loop) are set aside first. Of the others an edge's
    signs have to alternate, so one that repeats the sign before it is set aside, whether that one was accepted or not.
    """
    proper = F.coalesce((F.col("u") != F.col("v")) & F.col("sign").isin(1, -1) & F.col("seq").isNotNull(), F.lit(False))
    ends = {"_u": F.least("u", "v"), "_v": F.greatest("u", "v")}
    last = F.lag("sign", 1, -1).over(Window.partitionBy("_u", "_v").orderBy("seq"))
    marked = signed.where(proper).withColumns(ends).withColumn("_ok", F.col("sign") != last)
    events = marked.where("_ok").withColumns({"u": F.col("_u"), "v": F.col("_v")}).drop("_u", "_v", "_ok")
    return events, signed.where(~proper).unionByName(marked.where(~F.col("_ok")).drop("_u", "_v", "_ok"))


def with_deletions(inserts: DataFrame, delta: float, seed: int = 42) -> DataFrame:
    """A stream in which floor(delta * E) edges, those with the smallest keys, are deleted at random later places."""
    total = inserts.count()
    n = int(delta * total)
    keyed = inserts.select("seq", "ts", "u", "v", _number(seed, "chosen", F.col("u"), F.col("v")).alias("key"))
    chosen = numbered(keyed, ["key", "u", "v"], "rank").where(F.col("rank") < n)
    room = F.lit(total) - F.col("seq")
    late = chosen.select((F.col("seq") + 1 + _number(seed, "place", F.col("u"), F.col("v")) % room).alias("pos"), F.lit(0).alias("kind"), "ts", "u", "v", F.lit(-1).cast("byte").alias("sign"))
    # a deletion at place p comes before the insertion numbered p; p > seq, so it follows its own insertion
    all_ = inserts.select(F.col("seq").alias("pos"), F.lit(1).alias("kind"), "ts", "u", "v", F.lit(1).cast("byte").alias("sign")).unionByName(late)
    return numbered(all_, ["pos", "kind", "u", "v"]).select("seq", "ts", "u", "v", "sign")


def live_edges(signed: DataFrame) -> DataFrame:
    """Edges (u, v) present after the last event."""
    return signed.groupBy("u", "v").agg(F.sum("sign").alias("n")).where("n > 0").select("u", "v")


def lifetimes(signed: DataFrame) -> DataFrame:
    """(u, v, enter_seq, exit_seq): each insertion with the deletion that ends it, null if none does."""
    nxt = F.lead("seq").over(Window.partitionBy("u", "v").orderBy("seq"))
    return signed.withColumn("exit_seq", nxt).where("sign = 1").select("u", "v", F.col("seq").alias("enter_seq"), "exit_seq")

"""Mixing sources to target weights by a low-discrepancy schedule.

Each source's documents are shuffled by hash and laid end to end; the endless repetition of that stream is cut into
blocks of equal numbers of words. A source with target t needs the blocks 0 .. ceil(t / block) - 1. All needed blocks,
laid side by side by source, are the cumulative weights; a van der Corput sequence visits them, so any stretch of the
schedule has every source near its share. The points are used in reverse: block k of the N in all is visited at time
bit-reverse(k), which needs neither a range join nor a draw per slot.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import storage

WORDS = r"[^\x20\x09-\x0D]+"
BLOCK_WORDS = 1024
#: Documents, or slots, in one bucket of a two-step running sum.
BUCKET_ROWS = 4096


def n_words(text: str | Column) -> Column:
    """Words of a text; 0 for null."""
    return F.coalesce(F.regexp_count(text, F.lit(WORDS)), F.lit(0)).cast("long")


def targets(sizes: DataFrame, weights: tuple[float, ...] = (5, 2, 1), budget: float = 1.5, most: float = 2.0) -> DataFrame:
    """(source, source_size, target) from rows (source, size).

    Sources by code point, null last, take the weights in turn. They share ``budget`` times all sizes; a target stops
    at ``most`` times its source's size and the excess goes to the others by weight until none is above. That ends
    where targets are min(cap, level * weight): with sources in the order of cap / weight, those before a point are
    capped and the level follows from the rest. Only a row per source meets in a window.
    """
    sources = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    at = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod(at, F.lit(len(weights))) + 1).cast("int"))
    capped = sources.select("source", "source_size", weight.alias("weight"), (F.lit(float(most)) * F.col("source_size")).alias("cap"))
    order = Window.orderBy(F.col("cap") / F.col("weight"), F.col("source").asc_nulls_last())
    upto, everything = order.rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy()
    stepped = capped.select(
        "*",
        F.coalesce(F.sum("cap").over(upto), F.lit(0.0)).alias("below"),
        (F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(upto), F.lit(0.0))).alias("open"),
        (F.lit(float(budget)) * F.sum("source_size").over(everything)).alias("budget"),
    )
    # the level if exactly the sources before this one are capped; it holds at the first source that it leaves uncapped
    level = (F.col("budget") - F.col("below")) / F.col("open")
    fits = stepped.withColumn("level", F.when(level * F.col("weight") <= F.col("cap"), level))
    first = F.first("level", ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    return fits.withColumn("level", first).select("source", "source_size", F.when(F.col("level").isNull(), F.col("cap")).otherwise(F.least("cap", F.col("level") * F.col("weight"))).alias("target"))


def _summed(df: DataFrame, key: list[str], bucket: str, order: list[Column], value: Column, name: str) -> DataFrame:
    """Adds the sum of ``value`` over earlier rows of the key, by (bucket, order): inside buckets and over bucket totals."""
    totals = df.groupBy(*key, bucket).agg(F.sum(value).alias("_total"))
    before = Window.partitionBy(*key).orderBy(bucket).rowsBetween(Window.unboundedPreceding, -1)
    totals = totals.select(*[F.col(k).alias(f"_{k}") for k in key], F.col(bucket).alias("_bucket"), F.coalesce(F.sum("_total").over(before), F.lit(0)).alias("_before"))
    inside = Window.partitionBy(*key, bucket).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    own = df.withColumn("_inside", F.coalesce(F.sum(value).over(inside), F.lit(0)))
    same = [F.col(k).eqNullSafe(F.col(f"_{k}")) for k in key] + [F.col(bucket) == F.col("_bucket")]
    joined = own.join(totals, same)
    return joined.withColumn(name, F.col("_inside") + F.col("_before")).drop("_inside", "_before", "_bucket", *[f"_{k}" for k in key])


def schedule(goals: DataFrame, block_words: int = BLOCK_WORDS) -> DataFrame:
    """(source, rank, time) of every slot: at ``time`` the mix takes block ``rank`` of the source's stream.

    goals: source, target. Times are distinct, not dense.
    """
    need = F.ceil(F.floor("target") / F.lit(block_words)).cast("long")
    laid = goals.select("source", need.alias("need"))
    laid = laid.withColumn("first", F.coalesce(F.sum("need").over(Window.orderBy(F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    total = goals.agg(F.coalesce(F.sum(need), F.lit(0))).first()[0]
    bits = max(1, total.bit_length())
    chunk = F.explode(F.sequence(F.lit(0), F.col("need") - 1, F.lit(BUCKET_ROWS)))
    slots = laid.where("need > 0").select("source", "need", "first", chunk.alias("low")).repartition(max(1, min(512, total // (8 * BUCKET_ROWS))))
    slots = slots.select("source", F.explode(F.sequence(F.col("first") + F.col("low"), F.col("first") + F.least(F.col("low") + BUCKET_ROWS, F.col("need")) - 1)).alias("k"))
    spread = F.floor(F.col("k").cast("decimal(20,0)") * F.lit(1 << bits).cast("decimal(20,0)") / F.lit(max(total, 1))).cast("long")
    time = F.conv(F.reverse(F.lpad(F.bin(spread), bits, "0")), 2, 10).cast("long")
    slots = slots.select("source", time.alias("time"))
    slots = slots.withColumn("bucket", F.shiftright("time", max(0, bits - max(0, (total // BUCKET_ROWS).bit_length()))))
    return _summed(slots, ["source"], "bucket", [F.col("time")], F.lit(1), "rank").select("source", "rank", "time")


def mix(docs: DataFrame, weights: tuple[float, ...] = (5, 2, 1), budget: float = 1.5, most: float = 2.0, block_words: int = BLOCK_WORDS, seed: int = 42) -> tuple[DataFrame, DataFrame]:
    """(documents, pieces) of a mix of whole sources.

    docs: doc_id, source and text, any further columns. documents: row_hash, doc_id, source, size (words; null text:
    0), source_size, target, taken (words that the mix takes, repeats counted; at most ``most`` times size). pieces:
    time, source, doc_id, start, end: at each time of the schedule the words it takes. Null sources are one source,
    null ids are documents like any; repeated rows are laid one after the other; an empty table gives none. The order of a
    source depends on ids, texts and the seed alone, so reruns agree.
    """
    key = F.xxhash64(F.lit(seed), F.col("doc_id"), F.col("text"))
    sized = storage.saved(docs.select("doc_id", "source", n_words("text").alias("size"), key.alias("row_hash")), "sized")
    goals = storage.saved(targets(sized, weights, budget, most), "targets")
    rows = sized.count()
    bucket = F.shiftrightunsigned("row_hash", 64 - min(62, max(1, (rows // BUCKET_ROWS).bit_length())))
    placed = _summed(sized.withColumn("bucket", bucket), ["source"], "bucket", [F.col("row_hash"), F.col("doc_id")], F.col("size"), "at").drop("bucket")
    same = F.col("source").eqNullSafe(F.col("_source"))
    # a row per source, fewer than the sources' own documents: Spark broadcasts it only below its size limit
    placed = storage.saved(placed.join(goals.withColumnRenamed("source", "_source"), same).drop("_source"), "placed")
    limit = F.floor("target")
    repeats = F.when((F.col("size") > 0) & (F.col("at") < limit), F.sequence(F.lit(0), F.floor((limit - F.col("at") - 1) / F.col("source_size"))))
    taken = placed.where(repeats.isNotNull()).select("*", F.explode(repeats).alias("epoch"))
    low = F.col("at") + F.col("epoch") * F.col("source_size")
    taken = taken.select("*", low.alias("low"), F.least(low + F.col("size"), limit).alias("high"))
    blocks = F.sequence(F.floor(F.col("low") / block_words), F.floor((F.col("high") - 1) / block_words))
    taken = taken.select("*", F.explode(blocks).alias("rank"))
    slots = schedule(goals, block_words).select(F.col("source").alias("_source"), F.col("rank").alias("_rank"), "time")
    pieces = taken.join(slots, same & (F.col("rank") == F.col("_rank"))).select(
        "time", "row_hash", "doc_id", "source", "size", "source_size", "target", "at",
        (F.greatest("low", F.col("rank") * block_words) - F.col("low")).alias("start"),
        (F.least("high", (F.col("rank") + 1) * block_words) - F.col("low")).alias("end"),
    )
    names = ["row_hash", "doc_id", "source", "size", "source_size", "target"]
    summed = pieces.groupBy(*names, "at").agg(F.sum(F.col("end") - F.col("start")).alias("taken")).select(*names, "taken")
    rest = placed.where(repeats.isNull()).select(*names, F.lit(0).cast("long").alias("taken"))
    return summed.unionByName(rest), pieces.select("time", "source", "doc_id", "start", "end")


def mixed_rows(docs: DataFrame, **settings) -> DataFrame:
    """docs with each row as often as the mix takes it (taken / size, rounded), with docs' columns, whatever their names.

    Rows that are equal in doc_id and text share their takings evenly. Rows without words are never taken; an empty table
    gives none.
    """
    taken = mix(docs, **settings)[0]
    often = F.floor(F.avg(F.when(F.col("size") > 0, F.col("taken") / F.col("size")).otherwise(0.0)) + 0.5).cast("int")
    copies = taken.groupBy("row_hash").agg(often.alias("copies")).where("copies > 0")
    key = F.xxhash64(F.lit(settings.get("seed", 42)), F.col("doc_id"), F.col("text")).alias("row_hash")
    joined = docs.select(storage.packed(docs), key).join(copies, "row_hash")
    return joined.select("row", F.explode(F.sequence(F.lit(1), F.col("copies")))).select("row.*")

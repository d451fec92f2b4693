"""Samples as residency intervals: which edge is in which shard's sample from which event to which.

A reservoir is the bottom k of random keys over a prefix: a newcomer is among the k smallest of t with probability k / t and
pushes out the largest. This is deterministic, mergeable and free of draws that a re-run would repeat differently.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import BITS, draw_key
from ..sources.shared import cut
from .streams import number_within, running

#: Arrivals that one task of the first sampling step sees.
CHUNK = 1 << 17
#: Arrivals, in budgets, up to which a group has no level whose bound would take away much.
FEW = 16
#: Arrivals of a level that are expected below its threshold, in budgets.
SPARE = 2
#: Rows of a group on average from which a batch's groups are looked at as arrays.
LEAST_ROWS = 64
#: Events of a shard up to which its slots are found by a kernel.
KERNEL_EVENTS = 4_000_000


def run_numbers(runs: int | range) -> Column:
    """The numbers of runs, a row each: all below ``runs``, or those of a range."""
    return F.explode(F.array(*map(F.lit, range(runs) if isinstance(runs, int) else runs))).alias("run")


def storables(routed: DataFrame, runs: int | range, seed: int = 42, draws: str = "md5") -> DataFrame:
    """(run, shard, seq, u, v, t_local, key) for every run: storable insertions numbered from 1 at their shard."""
    local = routed if "t_local" in routed.columns else number_within(routed.select("shard", "seq", "u", "v"), ["shard"], "seq", "t_local")
    rows = local.select(run_numbers(runs), "shard", "seq", "u", "v", "t_local")
    return rows.withColumn("key", draw_key(F.col("run"), F.col("shard"), F.col("seq"), F.col("u"), F.col("v"), seed, draws))


def segment_storables(stored: DataFrame, t_star: int, max_sets: int | None) -> DataFrame:
    """Adds ``segment``: the sampling set that a storable falls in; a set is sealed after t_star arrivals while memory lasts."""
    segment = F.floor((F.col("t_local") - 1) / t_star)
    return stored.withColumn("segment", (segment if max_sets is None else F.least(segment, F.lit(max_sets - 1))).cast("int"))


def _entrants(seq: list[int], key: list[int], k: int) -> tuple[list[int], dict[int, int]]:
    """(indexes that enter the bottom k on arrival, index -> seq of the arrival that pushes it out) of one group; for tests."""
    heap: list[tuple[int, int]] = []
    entered, left = [], {}
    for i, x in enumerate(key):
        if len(heap) < k:
            heapq.heappush(heap, (-x, i))
        elif -heap[0][0] > x:
            left[heapq.heapreplace(heap, (-x, i))[1]] = seq[i]
        else:
            continue
        entered.append(i)
    return entered, left


def _reservoirs(batches: Iterator[pa.RecordBatch], k: int, n_group: int, ends: bool) -> Iterator[pa.RecordBatch]:
    """What enters the bottom k of each group; rows are sorted by group and seq, their columns group, payload, seq, key.

    ends: rows of group, payload, seq and the seq that pushes each out (null: none), else the rows themselves. Many small
    groups cost no more than one large one; what is held is one group's reservoir.
    """
    group, heap, n, out, schema = None, [], 0, [], None

    def batch(rows: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows), schema)], names=[*schema.names[:-1], "exit_seq" if ends else "key"])

    for own in batches:
        schema = own.schema
        if not len(own):
            continue
        groups, key = [c.to_numpy(zero_copy_only=False) for c in own.columns[:n_group]], own.columns[-1].to_numpy(zero_copy_only=False)
        cuts = np.flatnonzero(np.any([g[1:] != g[:-1] for g in groups], axis=0)) + 1
        if len(cuts) * LEAST_ROWS < len(own):
            # of long groups, only what fills the reservoir and keys below its largest are looked at
            for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), len(own)]):
                if (name := tuple(g[a].item() for g in groups)) != group:
                    if ends:
                        out += [(*x[:-1], None) for _, _, x in heap]
                    group, heap, n = name, [], 0
                fill = min(k - len(heap), b - a)
                if fill:
                    rows = list(zip(*(c.slice(a, fill).to_pylist() for c in own.columns)))
                    heap += [(-row[-1], n + i, row) for i, row in enumerate(rows, 1)]
                    heapq.heapify(heap)
                    out += [] if ends else rows
                some = a + fill + np.flatnonzero(key[a + fill : b] < -heap[0][0])
                for i, row in zip(some.tolist(), zip(*(c.take(pa.array(some)).to_pylist() for c in own.columns)) if len(some) else ()):
                    if -heap[0][0] > row[-1]:
                        gone = heapq.heapreplace(heap, (-row[-1], n + i - a + 1, row))[2]
                        out.append((*gone[:-1], row[-2]) if ends else row)
                n += b - a
            if len(out) > 10_000:
                yield batch(out)
                out = []
            continue
        for row in zip(*(c.to_pylist() for c in own.columns)):
            if row[:n_group] != group:
                if ends:
                    out += [(*x[:-1], None) for _, _, x in heap]
                group, heap, n = row[:n_group], [], 0
            n += 1
            if len(heap) < k:
                heapq.heappush(heap, (-row[-1], n, row))
            elif -heap[0][0] > row[-1]:
                gone = heapq.heapreplace(heap, (-row[-1], n, row))[2]
                if ends:
                    out.append((*gone[:-1], row[-2]))
            else:
                continue
            if not ends:
                out.append(row)
        if len(out) > 10_000:
            yield batch(out)
            out = []
    if ends:
        out += [(*x[:-1], None) for _, _, x in heap]
    if out:
        yield batch(out)


def reservoir_residency(stored: DataFrame, k: int, group: list[str], payload: list[str], most: int | None = None) -> DataFrame:
    """(*group, *payload, enter_seq, exit_seq) of what enters a reservoir of k within each group.

    stored: group, payload, seq, key, t_local (its number in the group or in a wider stream). Arrivals that cannot enter
    go first, by :func:`candidates`; chunks of the rest are reduced to their own entrants, which holds all that enter in
    the whole group; so a large group is split and what meets in one task is about 2 k log2(t / k) rows.
    most: arrivals that a group has at most (None: any number). Groups of a few budgets gain nothing by the first step, and
    those of one chunk, or with a budget of a chunk, nothing by the second, so these go without its passes over all arrivals.
    """
    if most is None or most > FEW * k:
        stored = candidates(stored, k, group)
    rows = stored.select(*group, *payload, "seq", F.col("key").cast("long").alias("key"))
    if k < CHUNK and (most is None or most > CHUNK):
        chunk = F.floor(F.col("seq") / CHUNK)
        parts = rows.select(*group, chunk.alias("_chunk"), *payload, "seq", "key")
        parts = parts.repartition(*group, "_chunk").sortWithinPartitions(*group, "_chunk", "seq")
        rows = parts.mapInArrow(lambda b: _reservoirs(b, k, len(group) + 1, False), parts.schema).drop("_chunk")
    rows = rows.repartition(*group).sortWithinPartitions(*group, "seq")
    out = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in stored.select(*group, *payload).schema.fields) + ", enter_seq long, exit_seq long"

    def settle(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in _reservoirs(batches, k, len(group), True):
            yield x.rename_columns(["enter_seq" if c == "seq" else c for c in x.schema.names])

    return rows.mapInArrow(settle, out)


def candidates(stored: DataFrame, k: int, group: list[str]) -> DataFrame:
    """Arrivals that may enter a reservoir of k; what it takes away never does.

    Arrivals fall in levels that double (by t_local). Keys below SPARE * k / size of a level are counted; where they are k or
    more, no later arrival with a key at or above that bound can be among the k smallest. One aggregation to a row per
    group and level, and a join back that is broadcast while those are few; nothing leaves the JVM.
    """
    if "t_local" not in stored.columns:
        return stored
    level = F.floor(F.log2(F.col("t_local").cast("double"))).cast("int")
    bound = F.floor(F.lit(float(SPARE * k)) * F.lit(float(1 << BITS)) / F.pow(F.lit(2.0), F.col("_level"))).cast("long")
    first = max(0, (4 * SPARE * k).bit_length())  # shorter levels have no use of a bound
    marked = stored.withColumn("_level", level)
    full = marked.where(F.col("_level") >= first).where(F.col("key") < bound).groupBy(*group, "_level").agg(F.count(F.lit(1)).alias("_n")).where(F.col("_n") >= k)
    # a level's bound holds for later ones, which mostly have a lower one of their own predecessor
    after = full.select(*group, (F.col("_level") + 1).alias("_level"), bound.alias("_bound"))
    return marked.join(after, [*group, "_level"], "left").where(F.col("_bound").isNull() | (F.col("key") < F.col("_bound"))).drop("_level", "_bound")


# ------------------------------------------------------------------ random pairing as slots


def assign_slots(stored: DataFrame, pairing: str = "queue", seed: int = 42, most: int | None = None) -> DataFrame:
    """(shard, u, v, ins_seq, del_seq, slot, fresh): the slot that each storable insertion takes.

    stored: shard, seq, u, v, sign. A deletion vacates its edge's slot; an insertion takes a vacant one if there is one, else it
    opens the next. queue: first vacated, first filled, by bucketed running sums and pointer doubling. random: a uniform vacancy, by
    a kernel for each shard. most: events that a shard has at most, if known; where these are few, queue has a kernel as well.
    """
    nxt = F.lead("seq").over(Window.partitionBy("shard", "u", "v").orderBy("seq"))
    rows = stored.select("shard", "seq", "u", "v", "sign", F.when(F.col("sign") == 1, nxt).alias("del_seq"))
    if pairing == "random":
        return rows.groupBy("shard").applyInPandas(lambda f: _random_slots(f, seed), "shard int, u long, v long, ins_seq long, del_seq long, slot long, fresh boolean")
    if most is not None and most <= KERNEL_EVENTS:
        return rows.groupBy("shard").applyInArrow(_queue_slots, "shard int, u long, v long, ins_seq long, del_seq long, slot long, fresh boolean")
    sign = F.col("sign").cast("long")
    rows = cut(running(rows, ["shard"], "seq", {"w": -sign, "vacated": (sign == -1).cast("long"), "filled": (sign == 1).cast("long")}))
    rows = running(rows, ["shard"], "seq", {}, {"earlier": F.col("w")})
    lowest = F.least(F.lit(0), F.coalesce("earlier", F.lit(0)))
    fresh = (F.col("sign") == 1) & (F.col("w") < lowest)
    # a new minimum of w opens a slot, so as many are open as w has been below 0; the other insertions reuse one
    rows = cut(rows.select("shard", "seq", "u", "v", "sign", "del_seq", "vacated", fresh.alias("fresh"), F.when(fresh, -F.col("w")).alias("slot"), (F.col("filled") + F.least(lowest, F.col("w"))).alias("reused")))
    inserts = rows.where("sign = 1")
    # the j-th insertion that reuses a slot takes that of the j-th deletion, hence of the edge which that ended
    ended = rows.where("sign = 1 and del_seq is not null").select("shard", F.col("del_seq").alias("at"), F.col("seq").alias("parent"))
    ends = rows.where("sign = -1").select("shard", F.col("vacated").alias("reused"), F.col("seq").alias("at")).join(ended, ["shard", "at"]).select("shard", "reused", "parent")
    link = cut(inserts.join(ends, ["shard", "reused"], "left").select("shard", F.col("seq").alias("ins_seq"), "slot", F.when(F.col("slot").isNull(), F.col("parent")).alias("parent")))
    while link.where("slot is null").take(1):  # doubles the distance to the chain's first insertion
        ahead = link.select("shard", F.col("ins_seq").alias("parent"), F.col("slot").alias("_slot"), F.col("parent").alias("_next"))
        link = cut(link.join(ahead, ["shard", "parent"], "left").select("shard", "ins_seq", F.coalesce("slot", "_slot").alias("slot"), F.when(F.coalesce("slot", "_slot").isNull(), F.col("_next")).alias("parent")))
    return inserts.select("shard", "u", "v", F.col("seq").alias("ins_seq"), "del_seq", "fresh").join(link.select("shard", "ins_seq", "slot"), ["shard", "ins_seq"]).select("shard", "u", "v", "ins_seq", "del_seq", "slot", "fresh")


def _queue_slots(table: pa.Table) -> pa.Table:
    """The slots of one shard: the j-th insertion that reuses one takes that of the j-th deletion, followed back to the insertion that opened it."""
    table = table.sort_by("seq")
    sign = table.column("sign").to_numpy().astype(np.int64)
    w = np.cumsum(-sign)
    fresh = (sign == 1) & (w < np.minimum(np.minimum.accumulate(np.r_[0, w[:-1]]), 0))
    ends = table.column("del_seq").fill_null(-1).to_numpy()
    ended = np.flatnonzero((sign == 1) & (ends >= 0))
    ended = ended[np.argsort(ends[ended], kind="stable")]
    reused = np.flatnonzero((sign == 1) & ~fresh)
    opener = np.arange(len(sign))
    opener[reused] = ended[: len(reused)]
    while not fresh[opener[reused]].all():
        opener = opener[opener]
    inserts = np.flatnonzero(sign == 1)
    out = table.take(pa.array(inserts))
    columns = [out.column("shard"), out.column("u"), out.column("v"), out.column("seq"), out.column("del_seq"), pa.array(-w[opener[inserts]]), pa.array(fresh[inserts])]
    return pa.table(columns, names=["shard", "u", "v", "ins_seq", "del_seq", "slot", "fresh"])


def _random_slots(frame: pd.DataFrame, seed: int) -> pd.DataFrame:
    import random

    frame = frame.sort_values("seq")
    shard = int(frame["shard"].iloc[0])
    draw = random.Random(f"{seed}|{shard}")
    at: dict[tuple[int, int], int] = {}
    vacant: list[int] = []
    opened, rows = 0, []
    for seq, u, v, sign, del_seq in frame[["seq", "u", "v", "sign", "del_seq"]].itertuples(index=False):
        if sign == -1:
            vacant.append(at.pop((u, v)))
            continue
        fresh = not vacant
        if fresh:
            opened += 1
            slot = opened
        else:
            k = draw.randrange(len(vacant))
            vacant[k], vacant[-1] = vacant[-1], vacant[k]
            slot = vacant.pop()
        at[u, v] = slot
        rows.append((shard, u, v, seq, None if pd.isna(del_seq) else int(del_seq), slot, fresh))
    out = pd.DataFrame(rows, columns=["shard", "u", "v", "ins_seq", "del_seq", "slot", "fresh"])
    out["del_seq"] = out["del_seq"].astype("Int64")
    return out


def slot_residency(slots: DataFrame, k: int, runs: int | range, seed: int = 42, draws: str = "md5", most: int | None = None) -> DataFrame:
    """(run, shard, slot, enter_seq, exit_seq) of slots that are among the k with the smallest keys opened so far; most: slots of a shard at most."""
    # the slots of a shard are numbered as they open
    fresh = slots.where("fresh").select(run_numbers(runs), "shard", "slot", F.col("ins_seq").alias("seq"), F.col("slot").alias("t_local"))
    keyed = fresh.withColumn("key", draw_key(F.col("run"), F.col("shard"), F.col("slot"), F.lit(0), F.lit(0), seed, draws))
    return reservoir_residency(keyed, k, ["run", "shard"], ["slot"], most)


def paired_residency(slots: DataFrame, k: int, runs: int | range, seed: int = 42, draws: str = "md5") -> DataFrame:
    """(run, shard, segment, u, v, enter_seq, exit_seq): occupants of the k slots with the smallest keys opened so far."""
    held = slot_residency(slots, k, runs, seed, draws).drop("enter_seq").withColumnRenamed("exit_seq", "slot_exit")
    rows = held.join(slots, ["shard", "slot"]).where("slot_exit is null or slot_exit > ins_seq")
    return rows.select("run", "shard", F.lit(0).alias("segment"), "u", "v", F.col("ins_seq").alias("enter_seq"), F.least("del_seq", "slot_exit").alias("exit_seq"))

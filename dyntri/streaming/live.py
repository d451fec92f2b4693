"""Estimates over unbounded streams: one state machine per shard, kept by Structured Streaming's state store."""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.replay import AdaptiveShard, PairedShard
from ..operators.routing import route_count

OUT = "shard int, events long, last_seq long, num string"


def _live(events: DataFrame, n_shards: int, make, seed: int) -> DataFrame:
    routed = route_count(events.select("seq", "u", "v", "sign"), n_shards, seed)

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        shard = int(key[0])
        machine, n, last = pickle.loads(state.get[0]) if state.exists else (make(shard), 0, -1)
        # a batch's events go by number; across batches the order of arrival is the stream's order
        for seq, u, v, sign, h_u, h_v in pd.concat(list(frames)).sort_values("seq")[["seq", "u", "v", "sign", "h_u", "h_v"]].itertuples(index=False):
            machine.event(int(seq), int(u), int(v), int(sign), shard in (h_u, h_v))
            n, last = n + 1, int(seq)
        state.update((pickle.dumps((machine, n, last)),))
        yield pd.DataFrame({"shard": [shard], "events": [n], "last_seq": [last], "num": [str(machine.total)]})

    return routed.groupBy("shard").applyInPandasWithState(step, OUT, "machine binary", "update", GroupStateTimeout.NoTimeout)


def adaptive_stream(events: DataFrame, n_shards: int, k: int, ratio_floor: float = 0.2, max_sets: int | None = None, seed: int = 42) -> DataFrame:
    """A streaming table (shard, events, last_seq, num) of each shard's running count over k^2 (k - 1).

    State is a shard's sample and counters, at most k edges for each of its sets. The layout's copies are inherent here:
    each state must see each event that may close a triangle, so shards are as many as cores, not thousands.
    """
    return _live(events, n_shards, lambda shard: AdaptiveShard(shard, k, ratio_floor, max_sets, seed), seed)


def dynamic_stream(events: DataFrame, n_shards: int, k: int, seed: int = 42) -> DataFrame:
    """The same for signed events, by random pairing; num is over k (k - 1)."""
    return _live(events, n_shards, lambda shard: PairedShard(shard, k, seed), seed)


def collected(latest: DataFrame, den: int) -> DataFrame:
    """(est): the collector. latest: the last row of each shard."""
    rows = latest.groupBy("shard").agg(F.max_by("num", "events").alias("num"))
    return rows.agg((F.coalesce(F.sum(F.col("num").cast("decimal(38,0)")), F.lit(0)).cast("double") / F.lit(float(den))).alias("est"))


def cleaned(pairs: DataFrame, watermark: str = "1 hour") -> DataFrame:
    """A stream of (ts, a, b) as canonical edges, late and repeated ones taken out within the watermark."""
    edges = pairs.where("a <> b").select("ts", F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v"))
    return edges.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["u", "v"])


def edge_rates(edges: DataFrame, size: str, slide: str | None = None) -> DataFrame:
    """(start, edges) by tumbling or sliding windows of event time."""
    window = F.window("ts", size, slide) if slide else F.window("ts", size)
    return edges.groupBy(window.alias("w")).agg(F.count(F.lit(1)).alias("edges")).select(F.col("w.start").alias("start"), "edges")

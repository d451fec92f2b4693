"""The estimators from SQL: a table function that runs one shard's state machine over each partition."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql.functions import udtf

from ..operators.replay import AdaptiveShard, PairedShard
from ..operators.routing import route_count

SCHEMA = "shard int, events long, num string"


class _Shards:
    def __init__(self):
        self.machine, self.shard, self.events = None, None, 0

    def _take(self, row: Row, make) -> None:
        if self.machine is None:
            self.shard = row["shard"]
            self.machine = make(self.shard)
        self.machine.event(row["seq"], row["u"], row["v"], row["sign"], self.shard in (row["h_u"], row["h_v"]))
        self.events += 1

    def terminate(self) -> Iterator[tuple]:
        if self.machine is not None:
            yield self.shard, self.events, str(self.machine.total)


class AdaptiveTriangles(_Shards):
    def eval(self, row: Row, k: int, ratio_floor: float):
        self._take(row, lambda shard: AdaptiveShard(shard, k, ratio_floor))


class PairedTriangles(_Shards):
    def eval(self, row: Row, k: int):
        self._take(row, lambda shard: PairedShard(shard, k))


def register_sql(spark: SparkSession) -> None:
    """Registers ``adaptive_shards(row, k, ratio_floor)`` and ``paired_shards(row, k)``.

    Both take a routed stream (register_routed) as ``TABLE(name) PARTITION BY shard ORDER BY seq`` and return a row per
    shard: shard, events, num, the numerator over k^2 (k - 1) or k (k - 1) as text. A shard's events meet in one task;
    the plans in ``methods`` don't need that.
    """
    spark.udtf.register("adaptive_shards", udtf(AdaptiveTriangles, returnType=SCHEMA))
    spark.udtf.register("paired_shards", udtf(PairedTriangles, returnType=SCHEMA))


def register_routed(events: DataFrame, n_shards: int, name: str, seed: int = 42) -> None:
    """A temporary view of the stream as the layout sends it to shards."""
    route_count(events.select("seq", "u", "v", "sign"), n_shards, seed).createOrReplaceTempView(name)


def adaptive_by_sql(events: DataFrame, n_shards: int, k: int, ratio_floor: float = 0.2) -> DataFrame:
    """(run, est), by SQL alone."""
    spark = events.sparkSession
    register_sql(spark)
    register_routed(events, n_shards, "routed_events")
    den = float(k * k * (k - 1))
    return spark.sql(f"""
        SELECT 0 AS run, CAST(coalesce(sum(CAST(num AS DECIMAL(38, 0))), 0) AS DOUBLE) / {den}D AS est
        FROM adaptive_shards(row => TABLE(routed_events) PARTITION BY shard ORDER BY seq, k => {k}, ratio_floor => {float(ratio_floor)}D)""")

"""Unbounded sources of edges, and sinks of estimates."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EVENT = "seq long, ts timestamp, u long, v long, sign byte"


def file_edges(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """Parquet files of events as they arrive, oldest first."""
    return spark.readStream.schema(EVENT).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def kafka_edges(spark: SparkSession, servers: str, topic: str, most_per_batch: int = 1_000_000) -> DataFrame:
    """Events as JSON values of a topic; needs Spark's Kafka package on the cluster. The offset is not the number of an event."""
    raw = spark.readStream.format("kafka").option("kafka.bootstrap.servers", servers).option("subscribe", topic).option("maxOffsetsPerTrigger", most_per_batch).load()
    return parsed(raw)


def parsed(raw: DataFrame) -> DataFrame:
    """Events from a binary or text column ``value`` of JSON; rows that are no event are left out."""
    return raw.select(F.from_json(F.col("value").cast("string"), EVENT).alias("e")).select("e.*").where("seq is not null and u is not null and v is not null")


def rate_edges(spark: SparkSession, per_second: int, vertices: int) -> DataFrame:
    """A load test: random edges among ``vertices``, insertions only."""
    rows = spark.readStream.format("rate").option("rowsPerSecond", per_second).load()
    end = lambda salt: F.pmod(F.xxhash64("value", F.lit(salt)), F.lit(vertices))
    return rows.select(F.col("value").alias("seq"), F.col("timestamp").alias("ts"), F.least(end(1), end(2)).alias("u"), F.greatest(end(1), end(2)).alias("v"), F.lit(1).cast("byte").alias("sign")).where("u < v")


def latest_sink(path: str) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: a batch's rows in a folder of its own, so a repeated batch replaces itself."""
    return lambda rows, batch: rows.write.mode("overwrite").parquet(f"{path}/batch={batch}")


def latest(spark: SparkSession, path: str, keys: list[str]) -> DataFrame:
    """The last row of each key of what latest_sink has written."""
    rows = spark.read.parquet(path)
    own = [c for c in rows.columns if c not in (*keys, "batch")]
    return rows.groupBy(*keys).agg(F.max_by(F.struct(*own), "batch").alias("_r")).select(*keys, "_r.*")


def write_runs(estimates: DataFrame, path: str) -> None:
    """Estimates as Parquet, a folder for each run."""
    estimates.write.mode("overwrite").partitionBy("run").parquet(path)

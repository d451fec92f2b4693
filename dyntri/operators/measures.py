"""Accuracy and cost measures of estimates against exact counts."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .streams import running


def mean_global_error(truth: DataFrame, est: DataFrame) -> DataFrame:
    """(mge): mean over runs of |x - estimate| / (x + 1). truth: triangles; est: run, est."""
    x = F.col("triangles").cast("double")
    return est.join(F.broadcast(truth), F.lit(True)).agg(F.avg(F.abs(x - F.col("est")) / (x + 1)).alias("mge"))


def global_variance(truth: DataFrame, est: DataFrame) -> DataFrame:
    """(gvar): mean squared deviation from the truth."""
    gap = F.col("triangles").cast("double") - F.col("est")
    return est.join(F.broadcast(truth), F.lit(True)).agg(F.avg(gap * gap).alias("gvar"))


def bias_report(truth: DataFrame, est: DataFrame) -> DataFrame:
    """(bias, stderr, z, sample_variance, squared_bias) over runs."""
    rows = est.join(F.broadcast(truth), F.lit(True)).agg((F.avg("est") - F.max("triangles")).alias("bias"), (F.stddev_samp("est") / F.sqrt(F.count(F.lit(1)))).alias("stderr"), F.var_samp("est").alias("sample_variance"))
    return rows.select("bias", "stderr", F.when(F.col("stderr") > 0, F.col("bias") / F.col("stderr")).alias("z"), "sample_variance", (F.col("bias") ** 2).alias("squared_bias"))


def _vertices(truth: DataFrame, local: DataFrame, runs: int) -> DataFrame:
    """(run, node, x, e) of every vertex in every run; a vertex without an estimate has 0."""
    every = truth.select("node", F.col("triangles").cast("double").alias("x"), F.explode(F.sequence(F.lit(0), F.lit(runs - 1))).alias("run"))
    return every.join(local.select("run", "node", F.col("est").alias("e")), ["run", "node"], "left").fillna({"e": 0.0})


def mean_local_error(truth: DataFrame, local: DataFrame, runs: int) -> DataFrame:
    """(mle): mean over runs and all vertices of |x - estimate| / (x + 1)."""
    by_run = _vertices(truth, local, runs).groupBy("run").agg(F.avg(F.abs(F.col("x") - F.col("e")) / (F.col("x") + 1)).alias("m"))
    return by_run.agg(F.avg("m").alias("mle"))


def pearson_local(truth: DataFrame, local: DataFrame, runs: int) -> DataFrame:
    """(pearson): mean over runs of the correlation between exact and estimated vertex counts; null if one is constant."""
    rows = _vertices(truth, local, runs).groupBy("run").agg(F.covar_pop("x", "e").alias("c"), F.stddev_pop("x").alias("sx"), F.stddev_pop("e").alias("se"))
    spread = F.col("sx") * F.col("se")
    return rows.agg(F.avg(F.when(spread > 0, F.col("c") / spread)).alias("pearson"))


def improvement(table: DataFrame, baseline: str, method: str, measure: str, cell: list[str]) -> DataFrame:
    """(*cell, factor): the baseline's measure over the method's in each cell of a grid."""
    a, b = (table.where(F.col("method") == m).select(*cell, F.col(measure).alias(n)) for m, n in ((baseline, "_a"), (method, "_b")))
    return a.join(b, cell).select(*cell, F.when(F.col("_b") > 0, F.col("_a") / F.col("_b")).alias("factor"))


def ratio_profile(residency: DataFrame, stored: DataFrame) -> DataFrame:
    """(run, shard, held, storables, ratio) at the end of a stream."""
    held = residency.where("exit_seq is null").groupBy("run", "shard").agg(F.count(F.lit(1)).alias("held"))
    seen = stored.groupBy("shard").agg(F.count(F.lit(1)).alias("storables"))
    return held.join(seen, "shard").select("run", "shard", "held", "storables", (F.col("held") / F.col("storables")).alias("ratio"))


def lowest_ratio(residency: DataFrame, stored: DataFrame, ratio_floor: float) -> DataFrame:
    """(run, shard, lowest, floor_held): the least share of storables that a shard held after any of them, and whether it kept the floor."""
    out = residency.where("exit_seq is not null").select("run", "shard", F.col("exit_seq").alias("seq"), F.lit(-1).alias("d"))
    steps = residency.select("run", "shard", F.col("enter_seq").alias("seq"), F.lit(1).alias("d")).unionByName(out).groupBy("run", "shard", "seq").agg(F.sum("d").alias("d"))
    arrived = stored.select("shard", "seq").join(residency.select("run", "shard").distinct(), "shard").join(steps, ["run", "shard", "seq"], "left")
    rows = running(arrived, ["run", "shard"], "seq", {"held": F.coalesce("d", F.lit(0)).cast("long"), "seen": F.lit(1).cast("long")})
    low = rows.groupBy("run", "shard").agg(F.min(F.col("held") / F.col("seen")).alias("low"))
    return low.select("run", "shard", F.round("low", 6).alias("lowest"), (F.col("low") >= float(ratio_floor)).alias("floor_held"))


def scaling_slope(table: DataFrame) -> DataFrame:
    """(slope, r2) of seconds over edges."""
    return table.agg(F.regr_slope("seconds", "edges").alias("slope"), F.regr_r2("seconds", "edges").alias("r2"))


def timed(df: DataFrame) -> float:
    """Seconds to compute every row of ``df``, which are then dropped."""
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began

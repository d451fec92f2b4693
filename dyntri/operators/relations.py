"""Relational views of edge streams: subgraphs, snapshots, profiles and rankings."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .exact import clustering, degrees, triangles
from .streams import live_edges


def closed_edges(edges: DataFrame) -> DataFrame:
    """(u, v), once each, of edges that are part of a triangle."""
    sides = F.explode(F.array(*[F.struct(F.col(x).alias("u"), F.col(y).alias("v")) for x, y in ("ab", "bc", "ac")]))
    return triangles(edges).select(sides.alias("e")).select("e.u", "e.v").distinct()


def open_edges(edges: DataFrame) -> DataFrame:
    """(u, v) of edges in no triangle."""
    return edges.select("u", "v").join(closed_edges(edges), ["u", "v"], "left_anti")


def closed_nodes(edges: DataFrame) -> DataFrame:
    """(node) of vertices with a triangle."""
    ends = triangles(edges).select(F.explode(F.array("a", "b", "c")).alias("node"))
    return degrees(edges).select("node").join(ends, "node", "left_semi")


def induced(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """Edges with both ends among ``nodes`` (node)."""
    own = nodes.select("node").distinct()
    return edges.join(own.withColumnRenamed("node", "u"), "u", "left_semi").join(own.withColumnRenamed("node", "v"), "v", "left_semi").select(*edges.columns)


def degree_histogram(edges: DataFrame) -> DataFrame:
    """(degree, nodes)."""
    return degrees(edges).groupBy("degree").agg(F.count(F.lit(1)).alias("nodes"))


def mean_clustering(edges: DataFrame) -> DataFrame:
    return clustering(edges).agg(F.round(F.avg("coefficient"), 4).alias("coefficient"))


def snapshot(signed: DataFrame, before: int) -> DataFrame:
    """Edges (u, v) live just before event number ``before``."""
    return live_edges(signed.where(F.col("seq") < before))


def kept_edges(signed: DataFrame, before: int) -> DataFrame:
    """Edges live both at a snapshot and at the end."""
    return snapshot(signed, before).intersect(live_edges(signed))


def lost_edges(signed: DataFrame, before: int) -> DataFrame:
    """Edges live at a snapshot and no more at the end."""
    return snapshot(signed, before).subtract(live_edges(signed))


def edges_by_date(events: DataFrame) -> DataFrame:
    """(year, month, edges) with totals by year and over all."""
    return events.rollup(F.year("ts").alias("year"), F.month("ts").alias("month")).agg(F.count(F.lit(1)).alias("edges"))


def estimated_transitivity(edges: DataFrame, est: DataFrame) -> DataFrame:
    """(run, transitivity) by estimated triangles over exact wedges, which need degrees only."""
    wedges = degrees(edges).agg(F.sum((F.col("degree") * (F.col("degree") - 1) / 2).cast("long")).alias("w"))
    return est.join(F.broadcast(wedges), F.lit(True)).select("run", F.round(F.when(F.col("w") > 0, 3 * F.col("est") / F.col("w")), 6).alias("transitivity"))


def top_estimated(local: DataFrame, n: int, run: int = 0) -> DataFrame:
    """(node, est) of the n vertices with the largest estimates, ties by node."""
    return local.where(F.col("run") == run).select("node", "est").orderBy(F.col("est").desc(), "node").limit(n)

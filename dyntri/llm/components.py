"""Connected components of a link table, by repeated contraction; nothing but row counts reaches the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def components(links: DataFrame) -> DataFrame:
    """(node, component) of every node in links (a, b): the smallest node reachable. Self-links and repeats are fine.

    Each round maps every node to the smallest of itself and its neighbours, and links the images. The smallest node
    of a component maps to itself, so what is left of the component at the end is that node. Each round's tables are
    checkpointed to the shared folder.
    """
    edges = links.select("a", "b").where("a <> b").distinct().checkpoint()
    labels = None
    while labels is None or edges.take(1):
        both = edges.union(edges.select("b", "a"))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("to")).checkpoint()
        if labels is None:  # all nodes are ends of links at first
            labels = least.select(F.col("a").alias("node"), F.col("to").alias("component"))
        else:
            onto = least.withColumnRenamed("a", "component")
            labels = labels.join(onto, "component", "left").select("node", F.coalesce("to", "component").alias("component")).checkpoint()
        moved = edges.join(least.select(F.col("a"), F.col("to").alias("x")), "a").join(least.select(F.col("a").alias("b"), F.col("to").alias("y")), "b")
        edges = moved.where("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct().checkpoint()
    return labels

"""Exact triangle counts in blocks; triangles themselves, and their lives, by degree-ordered wedge joins."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .blocks import counted
from .streams import lifetimes, number_within


def degrees(edges: DataFrame) -> DataFrame:
    ends = edges.select(F.explode(F.array("u", "v")).alias("node"))
    return ends.groupBy("node").agg(F.count(F.lit(1)).alias("degree"))


def triangles(edges: DataFrame) -> DataFrame:
    """(a, b, c), a < b < c, of every triangle; wedges open at the end of least degree, which bounds them by m^1.5."""
    deg = degrees(edges)
    du, dv = deg.select(F.col("node").alias("u"), F.col("degree").alias("du")), deg.select(F.col("node").alias("v"), F.col("degree").alias("dv"))
    rows = edges.select("u", "v").join(du, "u").join(dv, "v")
    first = (F.col("du") < F.col("dv")) | ((F.col("du") == F.col("dv")) & (F.col("u") < F.col("v")))
    out = rows.select(F.when(first, F.col("u")).otherwise(F.col("v")).alias("x"), F.when(first, F.col("v")).otherwise(F.col("u")).alias("y"))
    wedges = out.join(out.withColumnRenamed("y", "z"), "x").where("y < z")
    closed = wedges.join(edges.select(F.col("u").alias("y"), F.col("v").alias("z")), ["y", "z"])
    ends = F.array_sort(F.array("x", "y", "z"))
    return closed.select(ends[0].alias("a"), ends[1].alias("b"), ends[2].alias("c"))


def exact_global(edges: DataFrame) -> DataFrame:
    return counted(edges).agg(F.coalesce(F.sum("triangles"), F.lit(0)).alias("triangles"))


def exact_local(edges: DataFrame) -> DataFrame:
    """(node, triangles) of every vertex, those without a triangle as well."""
    counts = counted(edges, local=True).groupBy("node").agg(F.sum("triangles").alias("triangles"))
    return degrees(edges).select("node").join(counts, "node", "left").select("node", F.coalesce("triangles", F.lit(0)).alias("triangles"))


def exact_global_of_classes(classes: DataFrame, edges: DataFrame) -> DataFrame:
    """exact_global of a graph whose vertices come in classes (node, n): all of a class are linked, and all of classes with an edge.

    Three vertices of one class, two and one, or one each of three classes; where no class has two, edges are counted in blocks.
    """
    total = lambda df, x: df.agg(F.coalesce(F.sum(x), F.lit(0).cast("decimal(38,0)")).alias("triangles"))
    big = lambda c: F.col(c).cast("decimal(12,0)")
    if not classes.where("n > 1").take(1):
        return exact_global(edges)
    size = lambda c: classes.select(F.col("node").alias(c), F.col("n").alias(f"n_{c}"))
    whole = lambda x: x.cast("decimal(38,0)")
    n = big("n")
    one = total(classes.where("n > 2"), whole(F.floor(n * (n - 1) * (n - 2) / 6)))
    pairs = edges.join(size("u"), "u").join(size("v"), "v")
    two = total(pairs, whole(F.floor(big("n_u") * big("n_v") * (big("n_u") + big("n_v") - 2) / 2)))
    three = total(triangles(edges).join(size("a"), "a").join(size("b"), "b").join(size("c"), "c"), whole(big("n_a") * big("n_b") * big("n_c")))
    return one.unionByName(two).unionByName(three).agg(F.sum("triangles").cast("long").alias("triangles"))


def _lives(life: DataFrame) -> DataFrame:
    """(x, y, z, i1, o1, i2, o2, i3, o3, born, died) of triangles: the lives of (x, y), (x, z) and (y, z), and the stretch in which all three last.

    Wedges open at the end with fewer lives, as in :func:`triangles`, and only of edges that live at the same time.
    """
    deg = degrees(life)
    rows = life.join(deg.select(F.col("node").alias("u"), F.col("degree").alias("du")), "u").join(deg.select(F.col("node").alias("v"), F.col("degree").alias("dv")), "v")
    first = (F.col("du") < F.col("dv")) | ((F.col("du") == F.col("dv")) & (F.col("u") < F.col("v")))
    out = rows.select(F.when(first, F.col("u")).otherwise(F.col("v")).alias("x"), F.when(first, F.col("v")).otherwise(F.col("u")).alias("y"), F.col("enter_seq").alias("i1"), F.col("exit_seq").alias("o1"))
    other = out.select("x", F.col("y").alias("z"), F.col("i1").alias("i2"), F.col("o1").alias("o2"))
    died = F.least("o1", "o2")
    wedges = out.join(other, "x").where("y < z").where(died.isNull() | (F.greatest("i1", "i2") < died))
    closed = wedges.join(life.select(F.col("u").alias("y"), F.col("v").alias("z"), F.col("enter_seq").alias("i3"), F.col("exit_seq").alias("o3")), ["y", "z"])
    return closed.withColumns({"born": F.greatest("i1", "i2", "i3"), "died": F.least("o1", "o2", "o3")}).where("died is null or born < died")


def triangle_lives(signed: DataFrame) -> DataFrame:
    """(a, b, c, born, died): every stretch of events in which a triangle exists, from its last edge to its first end."""
    ends = F.array_sort(F.array("x", "y", "z"))
    return _lives(lifetimes(signed)).select(ends[0].alias("a"), ends[1].alias("b"), ends[2].alias("c"), "born", "died")


def closings(events: DataFrame) -> DataFrame:
    """(seq, sign, u, v, c, in_a, in_b): every triangle that an event (u, v) closes or opens again, and when its edges (u, c) and (v, c) came.

    What an estimator counts is among these, whatever it holds.
    """

    def by(seq: str, sign: int, p: str, q: str, c: str, in_p: str, in_q: str) -> Column:
        ahead = F.col(p) < F.col(q)
        ins = [F.when(ahead, F.col(x)).otherwise(F.col(y)).alias(name) for x, y, name in ((in_p, in_q, "in_a"), (in_q, in_p, "in_b"))]
        return F.struct(F.col(seq).alias("seq"), F.lit(sign).cast("byte").alias("sign"), F.least(p, q).alias("u"), F.greatest(p, q).alias("v"), F.col(c).alias("c"), *ins)

    def of(at: str, seq: str, sign: int) -> Column:
        first, second = F.col(f"{at}1") == F.col(seq), F.col(f"{at}2") == F.col(seq)
        return F.when(first, by(seq, sign, "x", "y", "z", "i2", "i3")).when(second, by(seq, sign, "x", "z", "y", "i1", "i3")).otherwise(by(seq, sign, "y", "z", "x", "i1", "i2"))

    ends = F.when(F.col("died").isNull(), F.array(of("i", "born", 1))).otherwise(F.array(of("i", "born", 1), of("o", "died", -1)))
    return _lives(lifetimes(events)).select(F.explode(ends).alias("e")).select("e.*")


def exact_dynamic(signed: DataFrame) -> DataFrame:
    """The triangle count after the last event."""
    return triangle_lives(signed).agg(F.count(F.when(F.col("died").isNull(), 1)).alias("triangles"))


def exact_local_dynamic(signed: DataFrame) -> DataFrame:
    """(node, triangles) after the last event, for every vertex ever seen."""
    live = triangle_lives(signed).where("died is null").select(F.explode(F.array("a", "b", "c")).alias("node")).groupBy("node").agg(F.count(F.lit(1)).alias("triangles"))
    return degrees(signed).select("node").join(live, "node", "left").select("node", F.coalesce("triangles", F.lit(0)).alias("triangles"))


def exact_trajectory(signed: DataFrame) -> DataFrame:
    """(seq, triangles) after each event that changed the count."""
    lives = triangle_lives(signed)
    steps = lives.select(F.col("born").alias("seq"), F.lit(1).alias("d")).unionByName(lives.where("died is not null").select(F.col("died").alias("seq"), F.lit(-1).alias("d")))
    steps = steps.groupBy("seq").agg(F.sum("d").alias("d")).withColumn("all", F.lit(0))
    return number_within(steps, ["all"], "seq", "triangles", F.col("d")).select("seq", "triangles")


def clustering(edges: DataFrame) -> DataFrame:
    """(node, degree, triangles, coefficient)."""
    rows = degrees(edges).join(exact_local(edges), "node")
    room = F.col("degree") * (F.col("degree") - 1)
    return rows.withColumn("coefficient", F.when(room > 0, F.round(2 * F.col("triangles") / room, 6)).otherwise(0.0))


def transitivity(edges: DataFrame) -> DataFrame:
    """(triangles, wedges, transitivity)."""
    rows = degrees(edges).join(exact_local(edges), "node")
    sums = rows.agg((F.sum("triangles") / 3).cast("long").alias("triangles"), F.sum((F.col("degree") * (F.col("degree") - 1) / 2).cast("long")).alias("wedges"))
    return sums.withColumn("transitivity", F.round(F.when(F.col("wedges") > 0, 3 * F.col("triangles") / F.col("wedges")), 6))


def top_local(edges: DataFrame, n: int) -> DataFrame:
    return exact_local(edges).orderBy(F.col("triangles").desc(), "node").limit(n)


def anomalies(edges: DataFrame) -> DataFrame:
    """(node, triangles, z): how far a vertex's count lies from the mean, in standard deviations."""
    rows = exact_local(edges)
    stats = rows.agg(F.avg("triangles").alias("m"), F.stddev_pop("triangles").alias("s"))
    return rows.join(F.broadcast(stats), F.lit(True)).select("node", "triangles", F.round(F.when(F.col("s") > 0, (F.col("triangles") - F.col("m")) / F.col("s")).otherwise(0.0), 6).alias("z"))


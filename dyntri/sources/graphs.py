"""Edge streams built from the tables: each gives (seq, ts, u, v, sign) in a total order."""

from __future__ import annotations

from collections.abc import Callable
from functools import wraps

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import _number
from ..operators.streams import canonical_edges, number_within, numbered, stream
from .shared import cut


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edge_list(spark: SparkSession, path: str, comment: str = "#") -> DataFrame:
    """(a, b, sign) from text lines of two ids and an optional sign, apart by blanks or commas."""
    parts = F.split(F.trim("value"), r"[\s,]+")
    lines = spark.read.text(path).where(~F.col("value").startswith(comment) & (F.trim("value") != ""))
    return lines.select(parts[0].cast("long").alias("a"), parts[1].cast("long").alias("b"), F.coalesce(F.get(parts, 2).cast("byte"), F.lit(1).cast("byte")).alias("sign"))


#: Canonical edges of a graph, and the columns that order its stream.
Canonical = tuple[DataFrame, list[str]]


def streamed(build: Callable[..., Canonical]) -> Callable[..., DataFrame]:
    """The numbered stream of a graph; its ``edges`` (u, v) alone need no order, hence none of the numbering's passes."""

    @wraps(build)
    def make(spark: SparkSession, sf_dir: str, **options) -> DataFrame:
        return stream(*build(spark, sf_dir, **options))

    make.edges = lambda spark, sf_dir, **options: build(spark, sf_dir, **options)[0].select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v"))
    return make


def _lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    items = read_table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey")
    orders = read_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", F.col("o_orderdate").alias("ts"))
    return items.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))


def _within(rows: DataFrame, key: list[str], item: str) -> DataFrame:
    """Pairs of distinct items that share a key: (a, b, ts), a < b."""
    own = rows.select(*key, F.col(item).alias("a"), "ts").distinct()
    return own.join(own.select(*key, F.col("a").alias("b")).distinct(), key).where("a < b").select("a", "b", "ts")


@streamed
def part_copurchase(spark: SparkSession, sf_dir: str) -> Canonical:
    return canonical_edges(_within(_lines(spark, sf_dir), ["l_orderkey"], "l_partkey"), ["ts"]), ["ts"]


@streamed
def supplier_cosupply(spark: SparkSession, sf_dir: str) -> Canonical:
    return canonical_edges(_within(_lines(spark, sf_dir), ["l_orderkey"], "l_suppkey"), ["ts"]), ["ts"]


@streamed
def trade_triads(spark: SparkSession, sf_dir: str) -> Canonical:
    ids = {"c": F.col("o_custkey") * 4, "p": F.col("l_partkey") * 4 + 1, "s": F.col("l_suppkey") * 4 + 2}
    sides = F.explode(F.array(*[F.struct(ids[x].alias("a"), ids[y].alias("b")) for x, y in ("cp", "ps", "cs")]))
    return canonical_edges(_lines(spark, sf_dir).select("ts", sides.alias("e")).select("e.a", "e.b", "ts"), ["ts"]), ["ts"]


@streamed
def customer_overlap(spark: SparkSession, sf_dir: str) -> Canonical:
    rows = _lines(spark, sf_dir).select("l_partkey", "o_custkey", F.date_trunc("month", "ts").alias("month"), F.date_trunc("month", "ts").alias("ts"))
    edges = canonical_edges(_within(rows, ["l_partkey", "month"], "o_custkey"), ["ts"])
    return edges.withColumn("h", _number("order", F.col("u"), F.col("v"))), ["h"]


@streamed
def user_handoff(spark: SparkSession, sf_dir: str) -> Canonical:
    """Users of consecutive events: neighbours inside a day, and the last event before each day's first."""
    rows = read_table(spark, sf_dir, "events").select("event_id", "ts", "user_id", F.date_trunc("day", "ts").alias("day"))
    order = Window.partitionBy("day").orderBy("ts", "event_id")
    last = rows.groupBy("day").agg(F.max(F.struct("ts", "event_id", "user_id")).alias("m"))
    carried = last.select(F.lead("day").over(Window.orderBy("day")).alias("day"), F.col("m.user_id").alias("carried")).where("day is not null")
    pairs = rows.withColumn("before", F.lag("user_id").over(order)).join(carried, "day", "left")
    return canonical_edges(pairs.select(F.coalesce("before", "carried").alias("a"), F.col("user_id").alias("b"), "ts", "event_id"), ["ts", "event_id"]), ["ts", "event_id"]


def encode_nodes(names: DataFrame) -> DataFrame:
    """(name, node): dense numbers of the distinct names in sorted order."""
    return numbered(names.select("name").distinct(), ["name"], "node")


def _links(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = read_table(spark, sf_dir, "pages").select("page_id", "url", "html")
    return pages.select("page_id", F.regexp_extract("url", "://([^/]*)", 1).alias("host"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("href"))


@streamed
def page_links(spark: SparkSession, sf_dir: str) -> Canonical:
    named = _links(spark, sf_dir).select("page_id", F.concat(F.lit("p"), F.col("page_id").cast("string")).alias("p"), F.concat(F.lit("h"), F.col("host")).alias("h"), F.concat(F.lit("l"), F.col("href")).alias("l"))
    sides = named.select("page_id", F.explode(F.array(*[F.struct(F.col(x).alias("x"), F.col(y).alias("y")) for x, y in ("ph", "pl", "hl")])).alias("e")).select("page_id", "e.x", "e.y").distinct()
    ids = encode_nodes(sides.select(F.explode(F.array("x", "y")).alias("name")))
    pairs = sides.join(ids.select(F.col("name").alias("x"), F.col("node").alias("a")), "x").join(ids.select(F.col("name").alias("y"), F.col("node").alias("b")), "y")
    return canonical_edges(pairs, ["page_id"]), ["page_id"]


@streamed
def page_overlap(spark: SparkSession, sf_dir: str) -> Canonical:
    rows = _links(spark, sf_dir).select("href", "page_id", F.lit(0).alias("ts"))
    return canonical_edges(_within(rows, ["href"], "page_id"), ["ts"]).drop("ts"), ["v"]


def page_twins(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """(classes, edges): pages with the same set of hrefs as (node, n), and the classes (u, v) that share an href.

    The pages of a class have the same neighbours and each other, so page_overlap is these edges and sizes, written out.
    """
    held = _links(spark, sf_dir).where("page_id is not null").groupBy("page_id").agg(F.array_sort(F.collect_set("href")).alias("hrefs"))
    same = held.groupBy(F.sha2(F.to_json("hrefs"), 256).alias("digest")).agg(F.min("page_id").cast("long").alias("node"), F.count(F.lit(1)).alias("n"), F.first("hrefs").alias("hrefs"))
    same = cut(same.select("node", "n", "hrefs"))
    rows = same.select(F.explode("hrefs").alias("href"), "node", F.lit(0).alias("ts"))
    return same.select("node", "n"), canonical_edges(_within(rows, ["href"], "node"), ["ts"]).select("u", "v")


#: Next holders of a line that a document is linked to.
HOLDERS = 8


@streamed
def doc_near_copies(spark: SparkSession, sf_dir: str) -> Canonical:
    """Documents that share a line of 40 characters or more, each with the next HOLDERS documents that have it.

    However many documents hold a line, its edges are in proportion to them, and none is left without any.
    """
    lines = read_table(spark, sf_dir, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).where(F.length("line") >= 40)
    held = lines.select(F.xxhash64("line").alias("line"), "doc_id").distinct()
    placed = cut(number_within(held, ["line"], "doc_id", "place"))
    ahead = placed.select("line", F.col("doc_id").alias("a"), F.explode(F.sequence(F.col("place") + 1, F.col("place") + HOLDERS)).alias("place"))
    pairs = ahead.join(placed.withColumnRenamed("doc_id", "b"), ["line", "place"]).select("a", "b", F.lit(0).alias("ts"))
    return canonical_edges(pairs, ["ts"]).drop("ts"), ["v"]


#: Vectors in one block of vector_neighbours.
BLOCK_VECTORS = 2048


@streamed
def vector_neighbours(spark: SparkSession, sf_dir: str, least: float = 0.3) -> Canonical:
    """Vectors with a cosine above ``least``, by products of blocks: a task holds two blocks, whatever the table's size.

    All blocks meet each other, as any exact answer needs; the work is spread evenly over as many tasks.
    """
    import numpy as np
    import pandas as pd

    rows = numbered(read_table(spark, sf_dir, "embeddings").select("vec_id", "embedding"), ["vec_id"], "place")
    rows = rows.withColumn("block", F.floor(F.col("place") / BLOCK_VECTORS)).select("block", "vec_id", F.col("embedding").cast("array<double>").alias("embedding"))

    def pack(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values("vec_id")
        matrix = np.stack(frame["embedding"].to_numpy())
        matrix = matrix / np.maximum(np.linalg.norm(matrix, axis=1, keepdims=True), 1e-300)
        return pd.DataFrame({"block": [frame["block"].iloc[0]], "ids": [frame["vec_id"].to_numpy(np.int64).tobytes()], "matrix": [matrix.tobytes()]})

    blocks = cut(rows.groupBy("block").applyInPandas(pack, "block long, ids binary, matrix binary"))
    n = blocks.count()
    met = spark.range(n).select(F.col("id").alias("block"), F.explode(F.sequence(F.col("id"), F.lit(n - 1).cast("long"))).alias("other"))
    other = blocks.select(F.col("block").alias("other"), F.col("ids").alias("other_ids"), F.col("matrix").alias("other_matrix"))
    both = met.join(blocks, "block").join(other, "other")

    def near(frames):
        for frame in frames:
            for x, xs, y, ys in frame[["ids", "matrix", "other_ids", "other_matrix"]].itertuples(index=False):
                x, y = np.frombuffer(x, np.int64), np.frombuffer(y, np.int64)
                i, j = np.nonzero(np.frombuffer(xs).reshape(len(x), -1) @ np.frombuffer(ys).reshape(len(y), -1).T > least)
                yield pd.DataFrame({"a": x[i], "b": y[j]})

    pairs = both.select("ids", "matrix", "other_ids", "other_matrix").mapInPandas(near, "a long, b long").where("a <> b")
    return canonical_edges(pairs.withColumn("ts_", F.lit(0)), ["ts_"]).drop("ts_"), ["u"]


GRAPHS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (part_copurchase, trade_triads, supplier_cosupply, customer_overlap, user_handoff, page_links, page_overlap, doc_near_copies, vector_neighbours)
}

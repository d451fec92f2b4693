"""N-gram Jaccard join: a blocked sparse product of the document by n-gram incidence matrix, with size bounds.

Rows of the matrix are distinct sets (copies with equal sets are one class from the start). Columns are ordered from
rare to frequent by a count sketch over the whole corpus; any fixed order is right, this one keeps blocks small. Two
sets of n and m columns with Jaccard >= t share at least ceil(t / (1 + t) * (n + m)) of them, hence at least one
among the first n - ceil(t * n) + 1 of each: only that part of the matrix is multiplied to find candidates.

Column by column, the product would list all pairs of a group of near copies. As only components are wanted, each
column first pairs its most central row (the one with fewest rarer columns before it) with all others: a product with
one row per column. What those links connect needs no further pair; then the remaining pairs, between different
components, are multiplied in full, their overlap counts summed over columns and cut by the bounds on what can follow.
Candidate pairs are then decided on whole sets, a block of pairs at a time. No pair that links two components is lost.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import arrow_text, storage
from .components import components

#: Slots of the count sketch that orders columns, and of one row of it while it is summed.
SLOTS, SLOT_ROW = 1 << 20, 1 << 12
#: Bits of the filter that picks candidates' texts: 16 per pair, at most this many.
FILTER_BITS = 1 << 27
#: Rounds of one central row per column before the full product of what is left.
HUB_ROUNDS = 4


def row_sets(column: pa.Array, size: int) -> Iterator[np.ndarray]:
    """The sorted distinct shingle hashes of each text."""
    table = arrow_text.word_table()
    codes = arrow_text.byte_codes(table)
    for _, _, data, offsets in arrow_text.text_pieces(column):
        starts, _, counts = arrow_text.word_spans(data, offsets, table)
        words = arrow_text.word_hashes(data, starts, codes)
        at = 0
        for n in counts.tolist():
            yield np.unique(arrow_text.shingle_hashes(words[at : at + n], size))
            at += n


def _slots(hashes: np.ndarray) -> np.ndarray:
    return (hashes >> np.uint64(24)).astype(np.int64) & (SLOTS - 1)


def column_counts(docs: DataFrame, size: int) -> np.ndarray:
    """How many sets have a column of each slot: a fixed-size sketch over all documents.

    Each task sums its own; rows of the sketch are then summed in two steps, so no task gets a row from every task.
    """

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(SLOTS, np.int64)
        for batch in batches:
            held, n = [], 0
            for s in row_sets(batch.column(0), size):
                held.append(_slots(s))
                n += len(s)
                if n > 1_000_000:
                    total += np.bincount(np.concatenate(held), minlength=SLOTS)
                    held, n = [], 0
            if held:
                total += np.bincount(np.concatenate(held), minlength=SLOTS)
        rows = np.arange(SLOTS // SLOT_ROW)
        yield pa.RecordBatch.from_arrays([pa.array(rows), pa.array([r.tobytes() for r in total.astype(np.int32).reshape(len(rows), -1)], pa.binary())], ["row", "counts"])

    def add(key: tuple, table: pa.Table) -> pa.Table:
        total = sum(np.frombuffer(x.as_py(), np.int32).astype(np.int64) for x in table.column("counts"))
        return pa.table({"row": pa.array([key[0].as_py()], pa.int64()), "counts": pa.array([np.minimum(total, 2**31 - 1).astype(np.int32).tobytes()], pa.binary())})

    schema = "row long, counts binary"
    parts = docs.select("text").mapInArrow(count, schema).withColumn("task", F.spark_partition_id() % 64)
    parts = parts.groupBy("row", "task").applyInArrow(lambda k, t: add(k, t), schema)
    rows = parts.groupBy("row").applyInArrow(lambda k, t: add(k, t), schema).collect()
    out = np.zeros((SLOTS // SLOT_ROW, SLOT_ROW), np.int32)
    for r in rows:
        out[r.row] = np.frombuffer(r.counts, np.int32)
    return out.reshape(-1)


def set_table(docs: DataFrame, size: int, percent: int, sketch) -> DataFrame:
    """(doc_id, n, digest, prefix): set size, a digest of the set, and the columns that candidates must share."""

    def describe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = sketch.value
        for batch in batches:
            sizes, digests, prefixes = [], [], []
            for s in row_sets(batch.column(1), size):
                n = len(s)
                sizes.append(n)
                digests.append(hashlib.blake2b(s.tobytes(), digest_size=16).digest())
                keep = n - -(-percent * n // 100) + 1 if n else 0
                order = np.argsort(counts[_slots(s)], kind="stable")[:keep]
                prefixes.append(s[order].view(np.int64))
            ends = np.cumsum([0, *map(len, prefixes)]).astype(np.int32)
            flat = np.concatenate(prefixes) if prefixes else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sizes, pa.int64()), pa.array(digests, pa.binary()), pa.ListArray.from_arrays(ends, flat)], ["doc_id", "n", "digest", "prefix"])

    return docs.select("doc_id", "text").mapInArrow(describe, "doc_id long, n long, digest binary, prefix array<long>")


def _needed(n: Column, m: Column, percent: int) -> Column:
    """The least overlap of two sets of these sizes that link."""
    return F.ceil(F.lit(percent) * (n + m) / F.lit(100 + percent))


def _may_link(na: Column, pa_: Column, nb: Column, pb: Column, percent: int) -> Column:
    """Size bound, and the bound on overlap from the columns where the two meet first."""
    fit = (100 * F.least(na, nb) >= percent * F.greatest(na, nb))
    return fit & (F.least(na - pa_, nb - pb) >= _needed(na, nb, percent))


def verified(pairs: DataFrame, docs: DataFrame, size: int, percent: int) -> DataFrame:
    """Of candidate pairs (a, b), those whose whole sets link.

    Sets are built anew for the documents that a filter of fixed size lets through; any size of it is right.
    """
    spark = docs.sparkSession
    ids = pairs.select(F.col("a").alias("id")).union(pairs.select("b"))
    bits = 1 << min(FILTER_BITS.bit_length() - 1, max(12, (16 * pairs.count()).bit_length()))
    slot = F.pmod(F.xxhash64("id"), F.lit(bits))
    words = ids.select(slot.alias("slot")).groupBy(F.shiftright("slot", 5).alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(slot % 32 as int))")).alias("bits")).toPandas()
    marks = np.zeros(bits // 32, np.uint32)
    marks[words["word"].to_numpy(np.int64)] = words["bits"].to_numpy(np.int64).astype(np.uint32)
    sent = spark.sparkContext.broadcast(marks)

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        marks = sent.value
        for batch in batches:
            slots = np.array(batch.column(2), np.int64)
            there = np.flatnonzero((marks[slots >> 5] >> (slots & 31).astype(np.uint32)) & 1)
            own = batch.take(pa.array(there))
            yield pa.RecordBatch.from_arrays([own.column(0), pa.array([s.tobytes() for s in row_sets(own.column(1), size)], pa.binary())], ["id", "columns"])

    marked = docs.where(F.col("doc_id").isNotNull()).select(F.col("doc_id").alias("id"), "text").withColumn("slot", slot)
    found = storage.saved(marked.mapInArrow(sets, "id long, columns binary"), "candidate_sets")

    def decide(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2), batch.column(3)):
                x, y = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                both = np.concatenate([x, y])
                both.sort()
                shared = int(np.count_nonzero(both[1:] == both[:-1]))
                keep.append(100 * shared >= percent * (len(x) + len(y) - shared))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], ["a", "b"]).filter(pa.array(keep, pa.bool_()))

    left = pairs.join(found.select(F.col("id").alias("b"), F.col("columns").alias("y")), "b")
    whole = left.join(found.select(F.col("id").alias("a"), F.col("columns").alias("x")), "a").select("a", "b", "x", "y")
    return whole.mapInArrow(decide, "a long, b long").distinct()


def _open_postings(shared: DataFrame, labels: DataFrame) -> DataFrame:
    """Postings of the columns that several components hold: comp, and the column's ``rows`` and ``main`` component, which has most of them."""
    rows = shared.join(labels, shared["rep"] == labels["node"], "left").withColumn("comp", F.coalesce("component", "rep"))
    held = rows.groupBy("h", "comp").agg(F.count(F.lit(1)).alias("n"))
    mixed = held.groupBy("h").agg(F.sum("n").alias("rows"), F.max(F.struct("n", "comp"))["comp"].alias("main"), F.count(F.lit(1)).alias("comps")).where("comps > 1")
    return storage.saved(rows.join(mixed.select("h", "rows", "main"), "h").select("h", "rep", "n", "pos", "first", "comp", "rows", "main"), "open_postings")


def _in_proportion(rows: DataFrame) -> bool:
    """Whether :func:`_cross_product` of these postings looks at few pairs for each of them."""
    stats = rows.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.when(F.col("comp") != F.col("main"), F.col("rows"))), F.lit(0))).first()
    return stats[1] <= 64 * (stats[0] + 100_000)


def _cross_product(rows: DataFrame, percent: int) -> DataFrame:
    """(a, b, n_a, n_b, pos_a, pos_b), a < b: the pairs of different components in a column that may link.

    A column's rows outside its main component meet all its rows, so the pairs within a large component are not made.
    """
    names = ("rep", "n", "pos", "comp")
    x = rows.where("comp <> main").select("h", "main", *[F.col(c).alias(f"{c}_x") for c in names])
    y = rows.select("h", *[F.col(c).alias(f"{c}_y") for c in names])
    # two rows outside the main component meet twice
    once = (F.col("comp_y") == F.col("main")) | (F.col("rep_x") < F.col("rep_y"))
    met = x.join(y, "h").where(once & (F.col("comp_x") != F.col("comp_y")))
    met = met.where(_may_link(F.col("n_x"), F.col("pos_x"), F.col("n_y"), F.col("pos_y"), percent))
    low = F.col("rep_x") < F.col("rep_y")
    sides = [F.when(low, F.col(f"{c}_{p}")).otherwise(F.col(f"{c}_{q}")).alias(name) for p, q, e in (("x", "y", "a"), ("y", "x", "b")) for c, name in (("rep", e), ("n", f"n_{e}"), ("pos", f"pos_{e}"))]
    return met.select(*sides)


def join_components(docs: DataFrame, size: int = 4, percent: int = 85) -> DataFrame:
    """(doc_id, n_shingles, component_id): set size, and the smallest doc_id reachable by links.

    docs: doc_id long, text string, any further columns (ignored). Two documents link where
    100 * overlap >= percent * union of their sets of ``size``-word shingles (A-Z lower-cased; a shorter text is one
    shingle). Null, empty and wordless texts have no shingle and link with nothing. Repeated rows give repeated rows;
    rows that share a doc_id are one node. A null doc_id takes part in no link; its component is null unless its set
    equals another document's. An empty table gives none.
    """
    spark = docs.sparkSession
    docs = docs.select("doc_id", "text")
    sketch = spark.sparkContext.broadcast(column_counts(docs, size))
    table = storage.saved(set_table(docs, size, percent, sketch), "sets")
    classes = storage.saved(table.where("n > 0").groupBy("digest").agg(F.min("doc_id").alias("rep")), "classes")
    own = table.where("n > 0").join(classes, "digest").where("doc_id = rep")
    postings = own.select("rep", "n", F.posexplode("prefix").alias("pos", "h"))
    often = postings.groupBy("h").agg(F.count(F.lit(1)).alias("rows"), F.min("pos").alias("first")).where("rows > 1")
    # the columns that two classes or more share; most have a single one and go here
    shared = storage.saved(postings.join(often.select("h", "first"), "h"), "postings")

    links, labels = None, None
    done = None
    for round_ in range(HUB_ROUNDS):
        if labels is None:
            rows = shared.withColumn("comp", F.col("rep"))
        else:
            rows = _open_postings(shared, labels)
            if _in_proportion(rows):
                break
        if labels is None:
            lead = rows.where("pos = first").groupBy("h").agg(F.min(F.struct("rep", "n", "pos", "comp")).alias("hub"))
        else:  # another row of each column, drawn by hash
            lead = rows.groupBy("h").agg(F.min(F.struct(F.xxhash64("rep", F.lit(round_)).alias("draw"), "rep", "n", "pos", "comp")).alias("hub"))
        star = rows.select("h", "rep", "n", "pos", "comp").join(lead, "h").where(F.col("comp") != F.col("hub.comp"))
        star = star.where(_may_link(F.col("n"), F.col("pos"), F.col("hub.n"), F.col("hub.pos"), percent))
        pairs = star.select(F.least("rep", "hub.rep").alias("a"), F.greatest("rep", "hub.rep").alias("b")).where("a <> b").distinct()
        pairs = storage.saved(pairs if done is None else pairs.join(done, ["a", "b"], "left_anti"), "star_pairs")
        done = pairs if done is None else done.union(pairs)
        new = storage.saved(verified(pairs, docs, size, percent), "links")
        links = new if links is None else links.union(new)
        labels = components(links)
    else:
        rows = _open_postings(shared, labels)

    met = _cross_product(rows, percent)
    counts = met.groupBy("a", "b", "n_a", "n_b").agg(F.count(F.lit(1)).alias("overlap"), F.max("pos_a").alias("last_a"), F.max("pos_b").alias("last_b"))
    room = F.col("overlap") + F.least(F.col("n_a") - 1 - F.col("last_a"), F.col("n_b") - 1 - F.col("last_b"))
    left = counts.where(room >= _needed(F.col("n_a"), F.col("n_b"), percent)).select("a", "b")
    left = storage.saved(left.join(done, ["a", "b"], "left_anti"), "cross_pairs")
    links = links.union(storage.saved(verified(left, docs, size, percent), "cross_links"))
    labels = components(links)
    named = classes.join(labels, classes["rep"] == labels["node"], "left").select("digest", F.coalesce("component", "rep").alias("component"))
    out = table.select("doc_id", "n", "digest").join(named, "digest", "left")
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("n") == 0, F.col("doc_id")).otherwise(F.col("component")).alias("component_id"))


def one_per_component(docs: DataFrame, size: int = 4, percent: int = 85) -> DataFrame:
    """The row of each component's smallest doc_id (a null one last), with docs' columns, whatever their names.

    Rows that share a doc_id, or have none, are documents of their own by text; where they tie, the smallest hash of the
    text stays. Of rows equal in doc_id and text one stays: the one with the smallest hash of all columns. Texts without
    words link with nothing and stay; an empty table gives none.
    """
    own = docs.select("doc_id", "text")
    several = storage.saved(own.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1 or doc_id is null").select("doc_id"), "repeated_ids")
    whole = docs.select(storage.packed(docs), F.col("doc_id").cast("long").alias("doc_id"), "text")
    version = F.xxhash64(F.col("doc_id").isNull(), "doc_id", F.col("text").isNull(), "text")
    if several.isEmpty():
        rows = whole.withColumn("node", F.col("doc_id"))
    else:
        again = several.select(F.col("doc_id").alias("id"), F.lit(True).alias("again"))
        rows = whole.join(again, F.col("doc_id").eqNullSafe(F.col("id")), "left").withColumn("node", F.when(F.col("again"), version).otherwise(F.col("doc_id"))).drop("id", "again")
        rows = storage.saved(rows, "nodes")
    found = join_components(rows.select(F.col("node").alias("doc_id"), "text"), size, percent).select(F.col("doc_id").alias("node"), "component_id").distinct()
    named = rows.select("node", "doc_id").distinct().join(found, "node")
    keep = named.groupBy("component_id").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "node"))["node"].alias("node")).select("node")
    there = rows.join(keep, "node", "left_semi")
    if several.isEmpty():
        return there.select("row.*")
    # only rows that are equal in doc_id and text share a node
    parts = F.struct(F.xxhash64(F.to_json("row")).alias("hash"), "row")
    return there.groupBy("node").agg(F.min_by("row", parts["hash"]).alias("row")).select("row.*")

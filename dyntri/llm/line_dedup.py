"""Line deduplication across documents by pairwise alignment.

Documents that share a run of adjacent lines are found by hashes of the shortest runs with enough words, from every line
on; they are aligned with a patience diff, common blocks that stand in another order are matched after it, and all of them
are deleted from the later document (the one with the larger doc_id). Every run that others have leads from each of its
holders to the first one, its smallest doc_id: as many pairs as holders, however frequent the run, and the first holder keeps
it. What is left is paired and aligned again until no two documents have a block of BLOCK_WORDS in common.
"""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import storage

#: Words that a run of lines (one long line or some short ones) needs to be a repeat, and those of a block of which no further copy stays either.
LINE_WORDS, BLOCK_WORDS = 5, 50
WORD = r"[^\x20\x09-\x0D]+"
#: The base of the rolling hash of runs, and its inverse modulo 2^64.
BASE = 0x9E3779B97F4A7C17
INVERSE = pow(BASE, -1, 1 << 64)


def aligned(a: list[int], b: list[int]) -> list[tuple[int, int]]:
    """Patience diff: half-open ranges of b that stand in a too, in the same order."""
    ranges: list[tuple[int, int]] = []
    for _, low, high in _blocks(a, b, a, b):
        if ranges and ranges[-1][1] == low:
            ranges[-1] = (ranges[-1][0], high)
        else:
            ranges.append((low, high))
    return ranges


def _blocks(a: list[int], b: list[int], a_keys: list, b_keys: list) -> list[tuple[int, int, int]]:
    """Common blocks in the order of both: place in a, place in b and end in b.

    Anchors are places by key and repetition number (the rare ones have a single repetition), None is no anchor; the
    longest increasing run of anchors is kept, then each grows over equal neighbours.
    """

    def numbered(keys: list) -> list[tuple]:
        seen: dict = {}
        out = []
        for i, x in enumerate(keys):
            if x is not None:
                seen[x] = k = seen.get(x, -1) + 1
                out.append(((x, k), i))
        return out

    place = dict(numbered(a_keys))
    anchors = [(place[key], j) for key, j in numbered(b_keys) if key in place]
    tails: list[int] = []
    ends: list[int] = []
    back = [-1] * len(anchors)
    for k, (i, _) in enumerate(anchors):
        at = bisect_left(tails, i)
        back[k] = ends[at - 1] if at else -1
        tails[at:at + 1] = [i]
        ends[at:at + 1] = [k]
    chain, k = [], ends[-1] if ends else -1
    while k >= 0:
        chain.append(anchors[k])
        k = back[k]
    found: list[tuple[int, int, int]] = []
    least = reach = 0
    for i, j in reversed(chain):
        if j < reach or i < least:
            continue
        n = 0
        while j - n > reach and i - n > least and a[i - n - 1] == b[j - n - 1]:
            n += 1
        high = j + 1
        while high < len(b) and i + (high - j) < len(a) and a[i + (high - j)] == b[high]:
            high += 1
        found.append((i - n, j - n, high))
        least, reach = i + (high - j), high
    return found


def _ends(words: np.ndarray, least: int) -> np.ndarray:
    """For every line the end of the shortest run from it on with ``least`` words, beyond the last line if there is none."""
    upto = np.concatenate([[0], np.cumsum(words, dtype=np.int64)])
    return np.searchsorted(upto, upto[:-1] + least)


def repeated(a: list[int], b: list[int], a_words: list[int], b_words: list[int], least: int, reuse: bool = False) -> list[int]:
    """The places in b of common blocks with ``least`` words: those in the order of a first, then the moved ones.

    A line of a stands for one line of b, with ``reuse`` for any number of them. No line is without words.
    """
    a_ends, b_ends = _ends(a_words, least).tolist(), _ends(b_words, least).tolist()
    a_keys = [tuple(a[i:e]) if e <= len(a) else None for i, e in enumerate(a_ends)]
    b_keys = [tuple(b[j:e]) if e <= len(b) else None for j, e in enumerate(b_ends)]
    used, gone = bytearray(len(a)), bytearray(len(b))
    for i, low, high in _blocks(a, b, a_keys, b_keys):
        gone[low:high] = b"\1" * (high - low)
        if not reuse:
            used[i:i + high - low] = b"\1" * (high - low)
    places: dict[tuple, list[int]] = {}
    for i in range(len(a) - 1, -1, -1):
        if a_keys[i] is not None:
            places.setdefault(a_keys[i], []).append(i)
    for j, key in enumerate(b_keys):
        own = places.get(key)
        if not own or 1 in gone[j:b_ends[j]]:
            continue
        while own and 1 in used[own[-1]:a_ends[own[-1]]]:
            own.pop()
        if not own:
            continue
        i, low, high = own[-1], j, b_ends[j]
        while low and i - (j - low) > 0 and not gone[low - 1] and not used[i - (j - low) - 1] and b[low - 1] == a[i - (j - low) - 1]:
            low -= 1
        while high < len(b) and i + (high - j) < len(a) and not gone[high] and not used[i + (high - j)] and b[high] == a[i + (high - j)]:
            high += 1
        gone[low:high] = b"\1" * (high - low)
        if not reuse:
            used[i - (j - low):i + (high - j)] = b"\1" * (high - low)
    return [j for j, x in enumerate(gone) if x]


# ------------------------------------------------------------------ kernels over batches

REST = "doc_id long, version long, lines array<long>, words array<short>, places array<int>"


def _lists(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Lengths and values of a column of arrays."""
    return column.value_lengths().fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64), column.flatten().to_numpy(zero_copy_only=False)


def _left(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """doc_id, version, lines, words, places, gone: the lines with words whose places are not gone."""
    for batch in batches:
        sizes, lines = _lists(batch.column(2))
        words, places = _lists(batch.column(3))[1], _lists(batch.column(4))[1].astype(np.int64)
        taken, gone = _lists(batch.column(5))
        rows = np.arange(batch.num_rows)
        row = np.repeat(rows, sizes)
        kept = (words > 0) & ~np.isin(row << 32 | places, np.repeat(rows, taken) << 32 | gone.astype(np.int64))
        cuts = pa.array(np.concatenate([[0], np.cumsum(np.bincount(row[kept], minlength=batch.num_rows))]), pa.int32())
        arrays = [pa.ListArray.from_arrays(cuts, pa.array(x[kept], kind)) for x, kind in ((lines, pa.int64()), (words, pa.int16()), (places, pa.int32()))]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *arrays], ["doc_id", "version", "lines", "words", "places"])


def _runs(batches: Iterator[pa.RecordBatch], least: int) -> Iterator[pa.RecordBatch]:
    """doc_id, lines, words: a hash of the shortest run with ``least`` words from every line on."""
    for batch in batches:
        sizes, lines = _lists(batch.column(1))
        words = _lists(batch.column(2))[1]
        n = len(lines)
        ends = _ends(words, least)
        own = np.flatnonzero(ends <= np.repeat(np.cumsum(sizes), sizes))
        powers, back = (np.concatenate([np.ones(1, np.uint64), np.cumprod(np.full(n, x, np.uint64))]) for x in (BASE, INVERSE))
        upto = np.concatenate([np.zeros(1, np.uint64), np.cumsum(lines.astype(np.int64).view(np.uint64) * powers[:n], dtype=np.uint64)])
        hashes = ((upto[ends[own]] - upto[own]) * back[own]).view(np.int64)
        doc = batch.column(0).take(pa.array(np.repeat(np.arange(batch.num_rows), sizes)[own]))
        yield pa.RecordBatch.from_arrays([doc, pa.array(hashes, pa.int64())], ["doc_id", "h"])


def _align(batches: Iterator[pa.RecordBatch], least: int, reuse: bool) -> Iterator[pa.RecordBatch]:
    """doc_id, version, lines, words, places, before, before_words: the places to be deleted, with the blank lines between them."""
    for batch in batches:
        found: list[list[int]] = []
        for b, b_words, places, a, a_words in zip(*(batch.column(k).to_pylist() for k in range(2, 7))):
            own = repeated(a, b, a_words, b_words, least, reuse)
            out = [places[j] for j in own[:1]]
            for last, j in zip(own, own[1:]):
                out += range(places[last] + 1, places[j] + 1) if j == last + 1 else [places[j]]
            found.append(out)
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(found, pa.list_(pa.int32()))], ["doc_id", "version", "gone"])


def deduplicated(docs: DataFrame, line_words: int = LINE_WORDS, block_words: int = BLOCK_WORDS) -> DataFrame:
    """docs with ``text`` less the lines that an earlier document has, and n_lines, removed_lines (sorted places).

    docs: doc_id, text, any further columns; columns with the added names give way. Lines are cut at \\n and compared
    without surrounding blanks; lines without words are passed over, and go where they stand within a block that goes. A
    block of common lines goes if it has ``line_words`` words or more, each line of the earlier document standing for one
    line; then, as often as there are any, all blocks of ``block_words`` in common go. Null texts stay null without lines,
    empty texts have one empty line; rows with a null doc_id stay as they are; rows with equal doc_ids are not compared
    with each other, so repeated rows all stay; an empty table gives none.
    """
    trimmed = F.transform(F.split("text", "\n"), lambda x: F.trim(F.translate(x, "\t\x0b\f\r", "    ")))
    words = F.transform(trimmed, lambda x: F.least(F.regexp_count(x, F.lit(WORD)), F.lit(32767)).cast("short"))
    hashed = docs.where("doc_id is not null and text is not null").select("doc_id", F.xxhash64("text").alias("version"), F.transform(trimmed, lambda x: F.xxhash64(x)).alias("lines"), words.alias("words"))
    whole = hashed.dropDuplicates(["doc_id", "version"]).select("*", F.sequence(F.lit(0), F.size("lines") - 1).alias("places"), F.array().cast("array<int>").alias("gone"))
    rest = storage.saved(whole.mapInArrow(_left, REST), "line_hashes")
    found: list[DataFrame] = []
    while True:
        least = block_words if found else line_words
        runs = rest.select("doc_id", "lines", "words").mapInArrow(partial(_runs, least=least), "doc_id long, h long")
        owners = runs.groupBy("h").agg(F.min("doc_id").alias("owner"), F.max("doc_id").alias("last")).where("owner < last")
        # one pair for all the runs that lead a document to one owner
        pairs = storage.saved(runs.join(owners.select("h", "owner"), "h").where("owner < doc_id").select("doc_id", "owner").distinct(), "line_pairs")
        if found and pairs.isEmpty():
            break
        before = rest.select(F.col("doc_id").alias("owner"), F.col("lines").alias("before"), F.col("words").alias("before_words"))
        both = pairs.join(rest, "doc_id").join(before, "owner").select("doc_id", "version", "lines", "words", "places", "before", "before_words")
        gone = both.mapInArrow(partial(_align, least=least, reuse=bool(found)), "doc_id long, version long, gone array<int>").where(F.size("gone") > 0)
        # a document's owners are no more than its lines
        gone = gone.groupBy("doc_id", "version").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("gone")))).alias("gone"))
        found.append(storage.saved(gone, "line_gone"))
        rest = storage.saved(rest.join(found[-1], ["doc_id", "version"], "left").select("doc_id", "version", "lines", "words", "places", "gone").mapInArrow(_left, REST), "line_rest")
    gone = found[0]
    for more in found[1:]:
        gone = gone.unionByName(more)
    if found[1:]:
        gone = gone.groupBy("doc_id", "version").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("gone")))).alias("gone"))
    gone = gone.select(F.col("doc_id").alias("id"), "version", "gone")
    kept = [c for c in docs.columns if c not in ("n_lines", "removed_lines")]
    own = docs.select(storage.packed(docs.select(*kept)), "doc_id", "text")
    joined = own.join(gone, (F.col("doc_id") == F.col("id")) & (F.xxhash64("text") == F.col("version")), "left")
    split = F.split("text", "\n")
    rest = F.array_join(F.transform(F.array_except(F.sequence(F.lit(0), F.size(split) - 1), F.col("gone")), lambda i: split[i]), "\n")
    text = F.when(F.col("gone").isNull(), F.col("text")).otherwise(rest)
    return joined.select(
        *[text.alias("text") if c == "text" else F.col("row")[c].alias(c) for c in kept],
        F.when(F.col("text").isNull(), 0).otherwise(F.size(split)).cast("long").alias("n_lines"),
        F.coalesce("gone", F.array().cast("array<int>")).alias("removed_lines"),
    )

"""Benchmark decontamination: one Aho-Corasick pass over normalised words, offsets mapped back to the original.

Normal form: A-Z lower-cased; words are runs of digits, a-z and non-ASCII characters, joined by single spaces. Every
``window`` consecutive words of a benchmark item make a pattern (a shorter item is one pattern of all its words).
"""

from __future__ import annotations

from collections.abc import Iterator
from uuid import uuid4

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import arrow_text, storage

NOT_WORD = bytes([*range(0x00, 0x30), *range(0x3A, 0x61), *range(0x7B, 0x80)])
NORMAL = bytes(b + 32 if 65 <= b <= 90 else 32 if b in NOT_WORD else b for b in range(256))
#: Benchmark text in one automaton, in bytes: a byte makes some 9 nodes of 40 bytes, so a worker holds about 200 MB at most.
BLOCK_BYTES = 500_000
#: Words of a part of an item; longer items are cut into parts that overlap by a window.
PART_WORDS = 20_000

ADDED = T.StructType(
    [
        T.StructField("n_words", T.LongType()),
        T.StructField("n_hit", T.LongType()),
        T.StructField("item_ids", T.ArrayType(T.StringType())),
        T.StructField("spans", T.ArrayType(T.StructType([T.StructField("start", T.LongType()), T.StructField("end", T.LongType())]))),
    ]
)


def normal_words(text: bytes) -> list[bytes]:
    return text.translate(NORMAL).split()


def patterns(items: list[tuple[str, bytes]], window: int) -> dict[str, list[int]]:
    """Pattern to the indexes of its items. Bytes are carried as Latin-1 text: a character is a byte."""
    found: dict[str, list[int]] = {}
    for k, (_, text) in enumerate(items):
        words = normal_words(text)
        size = min(window, len(words))
        for i in range(len(words) - size + 1 if size else 0):
            owners = found.setdefault((b" " + b" ".join(words[i : i + size]) + b" ").decode("latin-1"), [])
            if not owners or owners[-1] != k:
                owners.append(k)
    return found


_automata: dict[tuple, tuple] = {}


def automaton(items: list[tuple[str, bytes]], window: int, key: tuple):
    """The automaton of a block, built once per worker; None if it has no pattern."""
    if key not in _automata:
        import ahocorasick

        built = ahocorasick.Automaton()
        for p, owners in patterns(items, window).items():
            built.add_word(p, (len(p), p.count(" ") - 1, owners))
        if len(built):
            built.make_automaton()
        _automata.clear()
        _automata[key] = (built if len(built) else None,)
    return _automata[key][0]


def matches(built, text: bytes) -> tuple[int, list[tuple[int, int]], set[int]]:
    """(words, word ranges hit, item indexes) of a text; ranges are merged and half-open."""
    words = normal_words(text)
    if built is None or not words:
        return len(words), [], set()
    line = b" " + b" ".join(words) + b" "
    found = list(built.iter(line.decode("latin-1")))
    if not found:
        return len(words), [], set()
    spaces = np.flatnonzero(np.frombuffer(line, np.uint8) == 32)
    items: set[int] = set()
    ranges: list[tuple[int, int]] = []
    firsts = np.searchsorted(spaces, [end - size + 1 for end, (size, _, _) in found])
    for first, (_, (_, n, owners)) in zip(firsts.tolist(), found):
        items.update(owners)
        ranges.append((first, first + n))
    return len(words), merged(ranges), items


def merged(ranges: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted(ranges):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def spans(text: bytes, ranges: list[tuple[int, int]]) -> list[dict]:
    """Word ranges as code-point ranges of the original text."""
    data = np.frombuffer(text, np.uint8)
    starts, ends, _ = arrow_text.word_spans(data, np.array([0, len(data)]), arrow_text.word_table(NOT_WORD_CASED))
    points = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])
    return [{"start": int(points[starts[a]]), "end": int(points[ends[b - 1]])} for a, b in ranges]


NOT_WORD_CASED = bytes(b for b in NOT_WORD if not 65 <= b <= 90)


def scan(docs: DataFrame, benchmark: DataFrame, window: int = 10, keep: list[str] | None = None, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """Finds the benchmark in every whole text.

    docs: text string and any columns; benchmark: item_id, text. Returns the columns of docs (only those in ``keep``)
    and n_words, n_hit (words inside any pattern's occurrence), item_ids (of items with an occurrence, sorted as
    strings; a null id is "null"), spans (code-point ranges of the original text that were hit, merged). Columns of
    docs with these names give way. Null and empty texts, and those without words, have no hits; repeated rows each
    get their result; an empty benchmark hits nothing.

    The benchmark is split by hash into blocks whose text stays below ``block_bytes`` on average, long items by parts of
    PART_WORDS words; a block is one automaton. A single block is broadcast and applied in one pass without a shuffle. Of
    several, each is applied in a pass of its own that keeps hits only, by a 128-bit digest of the text; hits of all
    blocks then meet the texts in a join. So a worker holds one block at a time, whatever the benchmark's size.
    """
    items = _parts(benchmark, window)
    total = items.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    blocks = max(1, -(-total // block_bytes))
    keep = [c for c in (docs.columns if keep is None else keep) if c not in ADDED.names]
    schema = T.StructType([*[docs.schema[c] for c in keep], *ADDED.fields])
    if blocks == 1:
        return docs.select(*keep, F.col("text").alias(" text")).mapInArrow(_scanner(_sent(items), window, len(keep), schema.names), schema)
    keys = [F.xxhash64(F.lit(seed), "text").alias(f" key{seed}") for seed in (1, 2)]
    names = [" key1", " key2"]
    items = storage.saved(items.withColumn("block", F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks))), "benchmark_parts")
    found = None
    for k in range(blocks):
        hits = docs.where("text is not null").select(*keys, "text").mapInArrow(_finder(_sent(items.where(F.col("block") == k)), window), "` key1` long, ` key2` long, ranges array<long>, items array<string>")
        hits = storage.saved(hits.dropDuplicates(names), "benchmark_hits")
        found = hits if found is None else found.unionByName(hits)
    merged_ = found.groupBy(*names).agg(F.flatten(F.collect_list("ranges")).alias(" ranges"), F.array_distinct(F.flatten(F.collect_list("items"))).alias(" items"))
    joined = docs.select(*keep, F.col("text").alias(" text"), *keys).join(merged_, names, "left").drop(*names)
    return joined.select(*keep, " text", " ranges", " items").mapInArrow(_finisher(len(keep), schema.names), schema)


def _parts(benchmark: DataFrame, window: int) -> DataFrame:
    """(item_id string, text): items, those with more than PART_WORDS words in overlapping parts of normal words."""
    items = benchmark.select(F.coalesce(F.col("item_id").cast("string"), F.lit("null")).alias("item_id"), F.coalesce("text", F.lit("")).alias("text"))
    words = F.regexp_extract_all(F.col("text"), F.lit(r"([^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+)"), 1)
    own = items.withColumn("words", words)
    step = max(1, PART_WORDS - window + 1)
    starts = F.sequence(F.lit(1), F.greatest(F.size("words") - window + 1, F.lit(1)), F.lit(step))
    cut = F.transform(starts, lambda i: F.array_join(F.slice("words", i, PART_WORDS), " "))
    return own.select("item_id", F.explode(F.when(F.size("words") > PART_WORDS, cut).otherwise(F.array("text"))).alias("text"))


def _sent(items: DataFrame):
    """A block's items, sorted, for all workers; its size is bounded by the split into blocks."""
    return items.sparkSession.sparkContext.broadcast((uuid4().hex, sorted((r.item_id, r.text.encode()) for r in items.select("item_id", "text").collect())))


def _block(sent, window: int) -> tuple:
    """A block's items and its automaton."""
    name, items = sent.value
    return items, automaton(items, window, (name, window))


def _scanner(sent, window: int, kept: int, names: list[str]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        items, built = _block(sent, window)
        for batch in batches:
            found = []
            for text in batch.column(kept):
                data = text.as_buffer().to_pybytes() if text.is_valid else b""
                n, hit, got = matches(built, data)
                found.append((data, n, hit, sorted({items[k][0] for k in got})))
            yield pa.RecordBatch.from_arrays([*batch.columns[:kept], *_columns(found)], names=names)

    return run


def _finder(sent, window: int):
    """Keys, flat word ranges and items of the texts that have a hit."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        items, built = _block(sent, window)
        for batch in batches:
            rows, ranges, ids = [], [], []
            for k, text in enumerate(batch.column(2)):
                _, hit, got = matches(built, text.as_buffer().to_pybytes())
                if hit:
                    rows.append(k)
                    ranges.append([x for r in hit for x in r])
                    ids.append(sorted({items[j][0] for j in got}))
            own = batch.take(pa.array(rows, pa.int64()))
            yield pa.RecordBatch.from_arrays([own.column(0), own.column(1), pa.array(ranges, pa.list_(pa.int64())), pa.array(ids, pa.list_(pa.string()))], names=[" key1", " key2", "ranges", "items"])

    return run


def _finisher(kept: int, names: list[str]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = []
            for text, flat, ids in zip(batch.column(kept), batch.column(kept + 1).to_pylist(), batch.column(kept + 2).to_pylist()):
                data = text.as_buffer().to_pybytes() if text.is_valid else b""
                found.append((data, len(normal_words(data)), merged([*zip(flat[::2], flat[1::2])]) if flat else [], sorted(ids or [])))
            yield pa.RecordBatch.from_arrays([*batch.columns[:kept], *_columns(found)], names=names)

    return run


def _columns(found: list[tuple[bytes, int, list[tuple[int, int]], list[str]]]) -> list[pa.Array]:
    """The added columns of (text, words, word ranges hit, items)."""
    pair = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
    return [
        pa.array([n for _, n, _, _ in found], pa.int64()), pa.array([sum(b - a for a, b in hit) for _, _, hit, _ in found], pa.int64()),
        pa.array([ids for *_, ids in found], pa.list_(pa.string())), pa.array([spans(data, hit) if hit else [] for data, _, hit, _ in found], pair),
    ]


def clean(docs: DataFrame, benchmark: DataFrame, window: int = 10) -> DataFrame:
    """The rows of docs in which nothing of the benchmark occurs, with docs' columns, whatever their names.

    Null texts and texts without words stay; repeated rows stay or go together; an empty table gives none.
    """
    plain = docs.toDF(*["text" if c == "text" else f"c{k}" for k, c in enumerate(docs.columns)])
    return scan(plain, benchmark, window).where("n_hit = 0").select(*plain.columns).toDF(*docs.columns)


def digest(found: DataFrame) -> DataFrame:
    return found.select(
        "doc_id", "n_words", "n_hit", F.size("item_ids").cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", "item_ids").cast("binary"), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"),
    )

"""Token ids in binary files: Simple-8b words with block offsets, written and read by Spark.

File format (little-endian). A file is a run of segments, each followed by NUL bytes up to the next magic. A segment:

    magic        8 bytes  b"DTS8SEG1"
    counts       6 int64  documents, ids, dictionary entries, blocks, words, literals
    doc ids      int64 per document, then one byte per document: 1 where the id is null
    lengths      uint32 per document
    dictionary   uint32 per entry: entry r is the id that rank r stands for, most frequent first
    block starts uint32 per block: index of the block's first word (a block holds BLOCK_IDS ids)
    words        uint64 each: selector in the upper 4 bits, values below
    literals     uint64 each: values that no selector can hold

Ids are replaced by their frequency rank in the segment, so common ids take few bits. Selector s >= 1 packs
COUNTS[s] values of WIDTHS[s] bits; selector 0 is the escape, whose payload is an index into the literals.
A document's ids are found by its start in the segment: block = start // BLOCK_IDS, words from the block's start.
"""

from __future__ import annotations

import os
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import arrow_text, storage

MAGIC = b"DTS8SEG1"
BLOCK_IDS = 512
#: Values per word and bits per value, by selector; 0 is the escape.
COUNTS = np.array([1, 120, 60, 30, 20, 15, 12, 10, 8, 7, 6, 5, 4, 3, 2, 1])
WIDTHS = np.array([64, 0, 1, 2, 3, 4, 5, 6, 7, 8, 10, 12, 15, 20, 30, 60])
SEGMENT_IDS = 1 << 20
PIECE_BYTES = 1_000_000
#: Segments of a file, so files don't grow with the corpus, and bytes of a table's stored size that one writing task takes.
FILE_SEGMENTS, TASK_BYTES = 8, 64_000_000


# ------------------------------------------------------------------ the codec


def _bits(values: np.ndarray) -> np.ndarray:
    """Bit length of each value, exactly."""
    width = np.zeros(len(values), np.uint8)
    rest = values.copy()
    for step in (32, 16, 8, 4, 2, 1):
        big = rest >= np.uint64(1) << np.uint64(step)
        width[big] += step
        rest[big] >>= np.uint64(step)
    return width + (rest > 0).astype(np.uint8)


def _selectors(width: np.ndarray) -> np.ndarray:
    """For each position the selector that packs most values from there on, within its block."""
    n = len(width)
    blocks = np.full(-(-n // BLOCK_IDS) * BLOCK_IDS, 255, np.uint8)
    blocks[:n] = width
    reach = {1: blocks.reshape(-1, BLOCK_IDS)}

    def top(k: int) -> np.ndarray:
        """The widest of the k values from each position; 255 where they would leave the block."""
        if k not in reach:  # two overlapping or adjoining shorter windows
            low = top(half := 1 << ((k - 1).bit_length() - 1))
            out = np.full_like(low, 255)
            np.maximum(low[:, : half - k], low[:, k - half :], out=out[:, : half - k])
            reach[k] = out
        return reach[k]

    best = np.zeros(reach[1].shape, np.uint8)
    for s in range(len(COUNTS) - 1, 0, -1):
        np.putmask(best, top(int(COUNTS[s])) <= WIDTHS[s], s)
    return best.reshape(-1)[:n]


def pack(values: np.ndarray, width: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(words, block starts, literals) of unsigned 64-bit values; width: their bit lengths, if known."""
    values = np.ascontiguousarray(values, np.uint64)
    n = len(values)
    best = _selectors(_bits(values) if width is None else width)
    step = COUNTS[best]
    firsts = np.arange(0, n, BLOCK_IDS)
    at, ends, begins = firsts.copy(), np.minimum(firsts + BLOCK_IDS, n), np.zeros(n, bool)
    while len(at):  # all blocks step together, a word each time
        begins[at] = True
        at = at + step[at]
        live = at < ends
        at, ends = at[live], ends[live]
    starts = np.flatnonzero(begins)
    chosen = best[starts]
    words = chosen.astype(np.uint64) << np.uint64(60)
    for s in range(2, len(COUNTS)):
        rows = np.flatnonzero(chosen == s)
        if len(rows):
            first, word = starts[rows], words[rows]
            for k in range(int(COUNTS[s])):
                word |= values[first + k] << np.uint64(k * int(WIDTHS[s]))
            words[rows] = word
    rows = np.flatnonzero(chosen == 0)
    words[rows] |= np.arange(len(rows), dtype=np.uint64)
    return words, np.searchsorted(starts, firsts).astype(np.uint32), values[starts[rows]]


def unpack(words: np.ndarray, literals: np.ndarray) -> np.ndarray:
    """The values of consecutive words, all selectors at once."""
    chosen = (words >> np.uint64(60)).astype(np.int64)
    counts = COUNTS[chosen]
    ends = np.cumsum(counts)
    out = np.zeros(int(ends[-1]) if len(ends) else 0, np.uint64)
    starts = ends - counts
    for s in range(1, len(COUNTS)):
        if not WIDTHS[s]:
            continue
        rows = np.flatnonzero(chosen == s)
        mask = (np.uint64(1) << np.uint64(WIDTHS[s])) - np.uint64(1)
        for k in range(int(COUNTS[s])):
            out[starts[rows] + k] = words[rows] >> np.uint64(k * int(WIDTHS[s])) & mask
    rows = np.flatnonzero(chosen == 0)
    out[starts[rows]] = literals[(words[rows] & np.uint64((1 << 60) - 1)).astype(np.int64)]
    return out


def write_segment(doc_ids: np.ndarray, nulls: np.ndarray, lengths: np.ndarray, ids: np.ndarray) -> bytes:
    if len(ids) and int(ids.max()) < 1 << 22:
        often = np.bincount(ids)
        known, place = np.flatnonzero(often), ids
    else:
        known, place = np.unique(ids, return_inverse=True)
        often = np.bincount(place, minlength=len(known))
    order = np.argsort(-often[known] if place is ids else -often, kind="stable")
    rank = np.zeros(len(often), np.uint64)
    rank[known[order] if place is ids else order] = np.arange(len(known), dtype=np.uint64)
    words, blocks, literals = pack(rank[place], _bits(rank)[place])
    counts = np.array([len(doc_ids), len(ids), len(known), len(blocks), len(words), len(literals)], np.int64)
    parts = (counts, doc_ids.astype(np.int64), nulls.astype(np.uint8), lengths.astype(np.uint32), known[order].astype(np.uint32), blocks, words, literals)
    return MAGIC + b"".join(np.ascontiguousarray(x).tobytes() for x in parts)


def read_segments(content: bytes | pa.Buffer) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(doc ids, nulls, lengths, ids) of each segment of a file."""
    view, at = memoryview(content), 0
    while True:
        while at < len(view) and view[at] == 0:
            at += 1
        if at >= len(view):
            return
        if view[at : at + len(MAGIC)] != MAGIC:
            raise ValueError("not a segment of token ids")
        at += len(MAGIC)

        def take(kind: type, n: int) -> np.ndarray:
            nonlocal at
            got = np.frombuffer(view[at : at + n * np.dtype(kind).itemsize], kind)
            at += got.nbytes
            return got

        docs, n_ids, entries, blocks, n_words, n_literals = take(np.int64, 6).tolist()
        doc_ids, nulls, lengths = take(np.int64, docs), take(np.uint8, docs), take(np.uint32, docs)
        dictionary, _, words, literals = take(np.uint32, entries), take(np.uint32, blocks), take(np.uint64, n_words), take(np.uint64, n_literals)
        ids = dictionary[unpack(words, literals).astype(np.int64)] if n_ids else np.zeros(0, np.uint32)
        yield doc_ids, nulls, lengths, ids


def read_document(segment: bytes, index: int) -> np.ndarray:
    """The ids of one document of a segment: only the blocks that it touches are decoded."""
    counts = np.frombuffer(segment, np.int64, 6, len(MAGIC))
    docs, _, entries, blocks, n_words, n_literals = counts.tolist()
    at = len(MAGIC) + 48 + 9 * docs
    lengths = np.frombuffer(segment, np.uint32, docs, at).astype(np.int64)
    dictionary = np.frombuffer(segment, np.uint32, entries, at := at + 4 * docs)
    firsts = np.frombuffer(segment, np.uint32, blocks, at := at + 4 * entries)
    words = np.frombuffer(segment, np.uint64, n_words, at := at + 4 * blocks)
    literals = np.frombuffer(segment, np.uint64, n_literals, at + 8 * n_words)
    start = int(lengths[:index].sum())
    end = start + int(lengths[index])
    if start == end:
        return np.zeros(0, np.uint32)
    b0, b1 = start // BLOCK_IDS, (end - 1) // BLOCK_IDS + 1
    got = unpack(words[int(firsts[b0]) : int(firsts[b1]) if b1 < blocks else n_words], literals)
    return dictionary[got[start - b0 * BLOCK_IDS : end - b0 * BLOCK_IDS].astype(np.int64)]


# ------------------------------------------------------------------ tokenizing


class Grown:
    """An array that grows at its end."""

    def __init__(self, kind: type):
        self.data, self.n = np.empty(1024, kind), 0

    def __len__(self) -> int:
        return self.n

    def extend(self, more: np.ndarray) -> None:
        if self.n + len(more) > len(self.data):
            larger = np.empty(max(2 * len(self.data), self.n + len(more)), self.data.dtype)
            larger[: self.n] = self.data[: self.n]
            self.data = larger
        self.data[self.n : self.n + len(more)] = more
        self.n += len(more)

    def all(self) -> np.ndarray:
        return self.data[: self.n]


class WordTokenizer:
    """The ids of whole texts by a tokenizers-library file, with a memory of words.

    The file's tokenizer drops white space and never joins across it, so a text's ids are those of its
    space-separated words in turn. Words are found by 64-bit hashes of their bytes, many texts at a time; a new word
    goes to the library once. Plain Latin words are lower-cased and cut as the file's own pattern does, many at a time,
    and their pieces go to the file's model in one call; any other word takes the whole pipeline.
    """

    #: Words kept; beyond it the less used ones go, so a worker's memory stays at some 20 MB (two words of it meet in one hash with odds of 1e-9).
    KEPT = 120_000
    #: Endings that the file's pattern cuts off behind a word (a fixed value), and the kinds of characters that it tells apart.
    ENDINGS = ("s", "t", "re", "ve", "m", "ll", "d")
    LETTER, NUMBER, OTHER = 1, 2, 3

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        import regex
        from tokenizers import Tokenizer, pre_tokenizers

        self.tokenizer = Tokenizer.from_file(path)
        self.model = Tokenizer(self.tokenizer.model)
        self.model.pre_tokenizer = pre_tokenizers.WhitespaceSplit()
        # the last id of a piece is one whose entry has the suffix, no other is
        suffix = self.tokenizer.model.end_of_word_suffix
        self.last = np.zeros(self.tokenizer.get_vocab_size() + 1, bool)
        self.last[[i for t, i in self.tokenizer.get_vocab(False).items() if suffix and t.endswith(suffix)]] = True
        # byte-level alphabet: printable Latin-1 stands for itself, the other bytes for code points from 256 on; a space parts pieces
        plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
        rest = iter(range(256, 512))
        self.letters = np.array([b if b in plain else next(rest) for b in range(256)], "<u2")
        self.letters[32] = 32
        self.special = any(t.special for t in self.tokenizer.get_added_tokens_decoder().values())
        # kinds by code point, as far as plain words and their lower case go
        kinds = (("\\p{L}", self.LETTER), ("\\p{N}", self.NUMBER), ("[^\\s\\p{L}\\p{N}]", self.OTHER))
        self.kinds = np.zeros(0x2C80, np.uint8)
        for pattern, kind in kinds:
            self.kinds[[ord(c) for c in regex.findall(pattern, "".join(map(chr, range(len(self.kinds)))))]] = kind
        self._start()
        self.table = arrow_text.word_table()
        self.codes = arrow_text.byte_codes(self.table, lower=False)

    def _plain(self, text: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """Which words, each with a space behind it, are of printable characters below U+0250 that change one by one into lower case."""
        after = np.append(text[1:], np.uint8(32))
        odd = (text < 32) | (text == 127) | (text > 0xC9)
        for lead, wrong in ((0xC2, (after < 0xA1) | (after == 0xAD)), (0xC4, after == 0xB0), (0xC9, after > 0x8F)):
            odd |= (text == lead) & wrong
        if self.special:
            odd |= (text == ord("<")) & (after == ord("|"))
        return ~np.logical_or.reduceat(odd, starts)

    def _plain_ids(self, text: bytes) -> tuple[np.ndarray, np.ndarray] | None:
        """(ids, how many of each word) of plain words, each with a space behind it; None if the model's ids don't tell pieces apart."""
        lower = text.decode().lower()
        data, points = np.frombuffer(lower.encode(), np.uint8), np.frombuffer((lower + "  ").encode("utf-32-le"), np.uint32)
        kind = self.kinds[points]
        before = np.append(np.uint8(0), kind[:-1])
        begins = (kind > 0) & ((kind != before) | (kind == self.NUMBER))
        marks = np.flatnonzero((points == ord("'")) & (before != self.OTHER))
        for ending in self.ENDINGS:
            at = marks
            for k, c in enumerate(ending):
                at = at[points[at + 1 + k] == ord(c)]
            begins[at + 1] = False
            begins[at + 1 + len(ending)] = kind[at + 1 + len(ending)] > 0
        begins, kind = begins[:-2], kind[:-2]
        pieces = np.diff(np.append(0, np.cumsum(begins)[kind == 0]))
        inside = begins & (np.append(np.uint8(0), kind[:-1]) > 0)
        spaced = np.insert(data, np.flatnonzero((data & 0xC0) != 0x80)[inside], 32)
        encoded = self.model.encode_batch_fast([self.letters[spaced].tobytes().decode("utf-16-le")], add_special_tokens=False)
        ids = np.array(encoded[0].ids, np.uint32)
        ends = np.flatnonzero(self.last[ids]) + 1
        if len(ends) != pieces.sum() or ends[-1] != len(ids):
            return None
        return ids, np.diff(np.append(0, ends[np.cumsum(pieces) - 1]))

    def word(self, word: bytes) -> bytes:
        """The ids of a text without white space, 4 bytes each, by the whole pipeline."""
        return array("I", self.tokenizer.encode(word.decode(), add_special_tokens=False).ids).tobytes()

    def words(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(places of the words in the order that the rest has them, ids, how many of each word) of words between these places of data."""
        sizes = ends - starts
        first = np.cumsum(sizes + 1) - sizes - 1
        text = np.full(int(sizes.sum()) + len(sizes), 32, np.uint8)
        text[np.arange(len(text) - len(sizes)) + np.repeat(np.arange(len(sizes)), sizes)] = data[np.arange(len(text) - len(sizes)) + np.repeat(starts - first + np.arange(len(sizes)), sizes)]
        plain = self._plain(text, first)
        if plain.any() and (got := self._plain_ids(text[np.repeat(plain, sizes + 1)].tobytes())):
            ids, counts = got
        else:
            plain, ids, counts = np.zeros(len(sizes), bool), np.zeros(0, np.uint32), np.zeros(0, np.int64)
        other, raw = np.flatnonzero(~plain), text.tobytes()
        rest = [self.word(raw[a : a + n]) for a, n in zip(first[other].tolist(), sizes[other].tolist())]
        counts = np.append(counts, np.fromiter(map(len, rest), np.int64, len(rest)) // 4)
        return np.append(np.flatnonzero(plain), other), np.append(ids, np.frombuffer(b"".join(rest), np.uint32)), counts

    def _start(self) -> None:
        self.index = arrow_text.HashIndex(self.KEPT)
        self.flat, self.sizes, self.hashes = Grown(np.uint32), Grown(np.int64), Grown(np.uint64)
        self.uses = np.zeros(0, np.int64)

    def _forget(self) -> None:
        """Keeps the third of the words that was used most."""
        sizes, flat = self.sizes.all(), self.flat.all()
        best = np.sort(np.argsort(-self.uses, kind="stable")[: self.KEPT // 3])
        begins, hashes, uses = (np.cumsum(sizes) - sizes)[best], self.hashes.all()[best], self.uses[best] // 2
        sizes = sizes[best]
        ends = np.cumsum(sizes)
        kept = flat[np.arange(ends[-1] if len(ends) else 0) + np.repeat(begins - (ends - sizes), sizes)]
        self._start()
        self.index.add(hashes, np.arange(len(best)))
        self.flat.extend(kept)
        self.sizes.extend(sizes)
        self.hashes.extend(hashes)
        self.uses = uses

    def _learn(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray, hashes: np.ndarray) -> None:
        new, first = np.unique(hashes, return_index=True)
        place, ids, counts = self.words(data, starts[first], ends[first])
        self.index.add(new[place], len(self.sizes) + np.arange(len(new)))
        self.hashes.extend(new[place])
        self.sizes.extend(counts)
        self.flat.extend(ids)

    def ids(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids, how many of each row) for rows of bytes; a very long row is taken in stretches."""
        if len(data) > 2 * PIECE_BYTES and len(offsets) == 2:
            cuts = [0, *arrow_text.cut_points(data, self.table, PIECE_BYTES)]
            parts = [self.ids(data[a:b], np.array([0, b - a]))[0] for a, b in zip(cuts, cuts[1:])]
            whole = np.concatenate(parts)
            return whole, np.array([len(whole)])
        starts, ends, per_row = arrow_text.word_spans(data, offsets, self.table)
        if not len(starts):
            return np.zeros(0, np.uint32), np.zeros(len(per_row), np.int64)
        hashes = arrow_text.word_hashes(data, starts, self.codes)
        if len(self.sizes) > self.KEPT:
            self._forget()
        which = self.index.find(hashes)
        new = np.flatnonzero(which < 0)
        if len(new):
            self._learn(data, starts[new], ends[new], hashes[new])
            which[new] = self.index.find(hashes[new])
        sizes = self.sizes.all()
        self.uses = np.concatenate([self.uses, np.zeros(len(sizes) - len(self.uses), np.int64)]) + np.bincount(which, minlength=len(sizes))
        counts = sizes[which]
        total = np.cumsum(counts)
        begins = (np.cumsum(sizes) - sizes)[which]
        out = self.flat.all()[np.arange(total[-1]) + np.repeat(begins - (total - counts), counts)]
        upto = np.concatenate([[0], total])[np.concatenate([[0], np.cumsum(per_row)])]
        return out, np.diff(upto)


_tokenizers: dict[str, WordTokenizer] = {}


def tokenizer(path: str) -> WordTokenizer:
    """One per worker process and file."""
    if path not in _tokenizers:
        _tokenizers[path] = WordTokenizer(path)
    return _tokenizers[path]


# ------------------------------------------------------------------ the operator


def write_token_files(docs: DataFrame, path: str, tokenizer_path: str, end_id: int | None = 2, segment_ids: int = SEGMENT_IDS) -> None:
    """Tokenizes whole texts and writes their ids to ``path`` in ascending doc_id order (null ids first).

    docs: doc_id long, text string, any further columns. A null or empty text has the end id alone (nothing where
    ``end_id`` is None). Rows with equal ids go by a hash of the text, equal rows next to each other. An empty table
    writes no segment. One shuffle by ranges of doc_id and that hash, with as many tasks as the table's size asks for;
    each task then streams: at most one segment's ids are held, and FILE_SEGMENTS segments make a file.
    """

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok = tokenizer(tokenizer_path)
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = []
        size = 0

        def segment() -> pa.RecordBatch:
            blob = write_segment(*(np.concatenate(x) for x in zip(*held)))
            return pa.RecordBatch.from_arrays([pa.array([blob], pa.binary())], ["blob"])

        for batch in batches:
            doc_ids = batch.column(0)
            nulls, doc_ids = np.array(doc_ids.is_null()), np.array(pc.fill_null(doc_ids, 0))
            for a, b, data, offsets in arrow_text.text_pieces(batch.column(1), PIECE_BYTES):
                ids, counts = tok.ids(data, offsets)
                if end_id is not None:
                    ids = np.insert(ids, np.cumsum(counts), np.uint32(end_id))
                    counts = counts + 1
                held.append((doc_ids[a:b], nulls[a:b], counts, ids))
                size += len(ids)
                if size >= segment_ids:
                    yield segment()
                    held, size = [], 0
        if held:
            yield segment()

    n = storage.tasks(docs, TASK_BYTES)
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text"), F.xxhash64("text").alias("version"))
    ordered = own.repartitionByRange(n, "doc_id", "version").sortWithinPartitions("doc_id", "version", "text").select("doc_id", "text")
    storage.write_blobs(ordered.mapInArrow(encode, "blob binary"), "blob", path, per_file=FILE_SEGMENTS)


def read_token_files(spark, path: str) -> DataFrame:
    """(file int, place int, doc_id long, n_tokens long, ids array<long>) of all documents in ``path``."""
    return _read(spark, path, T.StructType([*_READ.fields, T.StructField("ids", T.ArrayType(T.LongType()))]), True)


def _file_number(path: str) -> int:
    """Task and number of a file within its task, as one number that orders files."""
    name = path.rpartition("/part-")[2]
    return int(name.split("-")[0]) << 24 | int(name.rpartition("-c")[2].split(".")[0])


_READ = T.StructType([T.StructField(n, T.LongType()) for n in ("file", "place", "doc_id", "n_tokens", "ids_crc32")])


def _read(spark, path: str, schema: T.StructType, whole: bool) -> DataFrame:
    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, content in zip(batch.column(0), batch.column(1)):
                file, place = _file_number(name.as_py()), 0
                for doc_ids, nulls, lengths, ids in read_segments(content.as_buffer()):
                    ends = np.cumsum(lengths, dtype=np.int64)
                    starts = ends - lengths
                    sums = [zlib.crc32(ids[a:b].tobytes()) for a, b in zip(starts.tolist(), ends.tolist())]
                    n = len(doc_ids)
                    columns = [pa.array(np.full(n, file)), pa.array(np.arange(place, place + n)), pa.array(doc_ids, mask=nulls.astype(bool)), pa.array(lengths.astype(np.int64)), pa.array(sums, pa.int64())]
                    if whole:
                        columns.append(pa.ListArray.from_arrays(np.append(starts, ends[-1:]).astype(np.int32), ids.astype(np.int64)))
                    place += n
                    yield pa.RecordBatch.from_arrays(columns, names=schema.names)

    return storage.read_blobs(spark, path).mapInArrow(decode, schema)


def token_digests(spark, path: str) -> DataFrame:
    """Per document, read from the files: doc_id, start (ids before it), n_tokens, ids_crc32.

    Starts: a running sum inside each file plus the totals of the files before it. Only the totals, a row per file,
    meet in one window; documents are windowed by file, and a file's size is bounded by its task's share.
    """
    from pyspark.sql import Window

    rows = storage.saved(_read(spark, path, _READ, False), "token_digests")
    inside = Window.partitionBy("file").orderBy("place").rowsBetween(Window.unboundedPreceding, -1)
    files = rows.groupBy("file").agg(F.sum("n_tokens").alias("total"))
    before = F.coalesce(F.sum("total").over(Window.orderBy("file").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    files = files.select("file", before.alias("before"))
    own = rows.withColumn("inside", F.coalesce(F.sum("n_tokens").over(inside), F.lit(0)))
    return own.join(files, "file").select("doc_id", (F.col("before") + F.col("inside")).alias("start"), "n_tokens", "ids_crc32")

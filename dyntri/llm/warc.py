"""WARC archives with a two-level capture index.

Archives: WARC 1.1 records, each a gzip member of its own, so any record can be read by its byte range. Equal payloads
are stored once: the record with the smallest id is a response, the others are revisits of it.

Index: a line per record, sorted by reversed-host key, in gzip blocks of ``BLOCK_LINES`` lines (the dense level), and
a directory with each block's first and last key, file and range (the sparse level). A look-up searches the directory,
then reads and searches the blocks that may hold its key, then reads the records' ranges: ``located`` for a table of
URLs, ``CaptureIndex`` for one.
"""

from __future__ import annotations

import base64
import hashlib
import json
import uuid
import zlib
from bisect import bisect_left, bisect_right
from collections.abc import Iterator
from urllib.parse import urlsplit

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import storage

BLOCK_LINES = 3000
#: Compressed bytes of an archive file.
FILE_BYTES = 16_000_000
#: Byte ranges, 16 bytes each, that may be sent to all executors.
SENT_RANGES = 2_000_000
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
SPACE_OF_IDS = uuid.UUID("6f2b8d0e-3c57-4d0f-9a3e-5b1f3f0c7a11")


def surt(url: str | None) -> str:
    """The reversed-host key of a URL: com,example,www)/path?query, without scheme, default port and fragment."""
    try:
        u = urlsplit((url or "").strip())
        host, port = (u.hostname or ""), u.port
    except ValueError:
        return (url or "").strip()
    if not host:
        return (url or "").strip()
    port = "" if port in (None, 80, 443) else f":{port}"
    return ",".join(reversed(host.split("."))) + f"{port})" + (u.path or "/") + (f"?{u.query}" if u.query else "")


def index_key(url: str | None) -> str:
    """The key under which the index has a URL as its record's header holds it."""
    return surt(None if url is None else _line(url)).replace("\t", "%09")


def record_id(page_id: int | None) -> str:
    return f"<urn:uuid:{uuid.uuid5(SPACE_OF_IDS, str(page_id))}>"


def _line(text: str) -> str:
    return text.replace("\r", "%0D").replace("\n", "%0A")


def record(page_id: int | None, url: str | None, payload: bytes, owner: int | None, date: str) -> bytes:
    """One gzip member. owner: the id that a revisit refers to, None for a response."""
    digest = base64.b32encode(hashlib.sha1(payload).digest()).decode()
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http if owner is not None else http + payload
    head = ["WARC/1.1", f"WARC-Type: {'response' if owner is None else 'revisit'}", f"WARC-Record-ID: {record_id(page_id)}", f"WARC-Date: {date}"]
    if url is not None:
        head.append(f"WARC-Target-URI: {_line(url)}")
    if owner is not None:
        head += [f"WARC-Profile: {PROFILE}", f"WARC-Refers-To: {record_id(owner)}", f"X-Refers-To-Page: {owner}"]
    head += [f"X-Page: {'' if page_id is None else page_id}", f"WARC-Payload-Digest: sha1:{digest}", "Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return _member("\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n")


def _member(data: bytes) -> bytes:
    z = zlib.compressobj(6, zlib.DEFLATED, 31)
    return z.compress(data) + z.flush()


def _info(date: str) -> bytes:
    body = b"format: WARC File Format 1.1\r\n"
    head = f"WARC/1.1\r\nWARC-Type: warcinfo\r\nWARC-Record-ID: <urn:uuid:{uuid.uuid5(SPACE_OF_IDS, 'info')}>\r\nWARC-Date: {date}\r\nContent-Type: application/warc-fields\r\nContent-Length: {len(body)}\r\n\r\n"
    return _member(head.encode() + body + b"\r\n\r\n")


def members(content: bytes) -> Iterator[tuple[int, int, bytes]]:
    """(offset, length, data) of the gzip members of a file; NUL padding between them is passed over."""
    at, view = 0, memoryview(content)
    while True:
        while at < len(content) and content[at] == 0:
            at += 1
        if at >= len(content):
            return
        z, parts, begin, step = zlib.decompressobj(31), [], at, 1 << 16
        while not z.eof:
            if at >= len(content):
                raise ValueError("a gzip member is cut off")
            parts.append(z.decompress(view[at : at + step]))
            at = min(at + step, len(content))
        at -= len(z.unused_data)
        yield begin, at - begin, b"".join(parts)


def parsed(data: bytes) -> tuple[dict[str, str], bytes]:
    """(header fields, block) of a record; the block is checked against Content-Length."""
    head, _, rest = data.partition(b"\r\n\r\n")
    lines = head.decode().split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError("not a WARC record")
    fields = {k: v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
    n = int(fields["Content-Length"])
    if rest[n:] != b"\r\n\r\n":
        raise ValueError("a record's length is wrong")
    return fields, rest[:n]


# ------------------------------------------------------------------ writing


def write_archives(pages: DataFrame, path: str, min_bytes: int = 0, date: str = "2024-01-01T00:00:00Z", file_bytes: int = FILE_BYTES) -> None:
    """A record per row of pages (page_id, url, html; further columns are ignored) in archive files below ``path``.

    A null html is an empty payload, a null url leaves the target out, a null page_id is a response always. Payloads
    of ``min_bytes`` and more that are equal are stored once, under the smallest page_id; equal rows are all responses.
    Payloads meet by digest only, summed up before the shuffle; the list of revisits is then joined to pages by id.
    """
    rows = pages.select("page_id", "url", F.coalesce("html", F.lit("")).alias("html"))
    seen = rows.where(F.octet_length("html") >= min_bytes).select("page_id", F.unhex(F.sha1(F.encode("html", "UTF-8"))).alias("digest"))
    owners = seen.groupBy("digest").agg(F.min("page_id").alias("owner"), F.max("page_id").alias("last")).where("owner < last").select("digest", "owner")
    # ids of copies alone; equal rows of one id count once
    again = storage.saved(seen.join(owners, "digest").where("page_id <> owner").select(F.col("page_id").alias("copy"), "digest", "owner"), "revisits")
    own = F.when(F.octet_length("html") >= min_bytes, F.unhex(F.sha1(F.encode("html", "UTF-8"))))
    keyed = rows.join(again.dropDuplicates(["copy", "digest"]), (F.col("page_id") == F.col("copy")) & (own == F.col("digest")), "left")

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, size = [], 0
        for batch in batches:
            for page_id, url, html, owner in zip(batch.column(0), batch.column(1), batch.column(2), batch.column(3)):
                if not parts:
                    parts.append(_info(date))
                parts.append(record(page_id.as_py(), url.as_py(), html.as_buffer().to_pybytes(), owner.as_py(), date))
                size += len(parts[-1])
                if size >= file_bytes:
                    yield pa.RecordBatch.from_arrays([pa.array([b"".join(parts)], pa.binary())], ["blob"])
                    parts, size = [], 0
        if parts:
            yield pa.RecordBatch.from_arrays([pa.array([b"".join(parts)], pa.binary())], ["blob"])

    storage.write_blobs(keyed.select("page_id", "url", "html", "owner").mapInArrow(write, "blob binary"), "blob", path, per_file=1)


# ------------------------------------------------------------------ the index

_LINES = "key string, page_id long, file string, offset long, length long, kind string, digest string"


def _index_lines(spark: SparkSession, path: str) -> DataFrame:
    names = [x.split()[0] for x in _LINES.split(", ")]

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for file, content in zip(batch.column(0).to_pylist(), batch.column(1)):
                rows = []
                for offset, length, data in members(content.as_buffer().to_pybytes()):
                    fields, _ = parsed(data)
                    if fields["WARC-Type"] != "warcinfo":
                        page = fields["X-Page"]
                        rows.append((index_key(fields.get("WARC-Target-URI")), int(page) if page else None, file, offset, length, fields["WARC-Type"], fields["WARC-Payload-Digest"]))
                kinds = [pa.string(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows) if rows else [()] * 7, kinds)], names)

    return storage.read_blobs(spark, path).mapInArrow(scan, _LINES)


def write_index(spark: SparkSession, archives: str, path: str, block_lines: int = BLOCK_LINES) -> None:
    """Writes ``path``/blocks (dense level) and ``path``/directory (sparse level) for the archives."""

    def block(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lines: list[str] = []

        def full() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([_member("".join(lines).encode())], pa.binary())], ["blob"])

        for batch in batches:
            for row in batch.to_pylist():
                lines.append(row.pop("key") + "\t" + json.dumps(row) + "\n")
                if len(lines) >= block_lines:
                    yield full()
                    lines = []
        if lines:
            yield full()

    n = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 1)
    lines = storage.saved(_index_lines(spark, archives), "index_lines")
    # urls repeat, and one of them may be very common: the id cuts it into ranges
    ordered = lines.repartitionByRange(n, "key", "page_id").sortWithinPartitions("key", "page_id", "file", "offset")
    storage.write_blobs(ordered.mapInArrow(block, "blob binary"), "blob", f"{path}/blocks")
    schema = "first_key string, last_key string, file string, offset long, length long"
    kinds = [pa.string(), pa.string(), pa.string(), pa.int64(), pa.int64()]

    def sparse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for file, content in zip(batch.column(0).to_pylist(), batch.column(1)):
                rows = []
                for at, n, data in members(content.as_buffer().to_pybytes()):
                    keys = _keys(_block_lines(data))
                    rows.append((keys[0], keys[-1], file, at, n))
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows) if rows else [()] * 5, kinds)], [x.split()[0] for x in schema.split(", ")])

    storage.read_blobs(spark, f"{path}/blocks").mapInArrow(sparse, schema).write.parquet(f"{path}/directory")


def _block_lines(data: bytes) -> list[str]:
    return data.decode().split("\n")[:-1]


def _keys(lines: list[str]) -> list[str]:
    return [x.split("\t", 1)[0] for x in lines]


def _covering(firsts: list[str], lasts: list[str], key: str) -> range:
    """Places, among ranges of keys in order, of those that may hold the key; a common key covers several."""
    return range(bisect_left(lasts, key), bisect_right(firsts, key))


def _files_of_blocks(directory: DataFrame) -> tuple[list[str], list[str], list[str]]:
    """(first keys, last keys, names) of the block files in key order: one row for each task that wrote the index."""
    bounds = directory.groupBy("file").agg(F.min("first_key").alias("first"), F.max("last_key").alias("last"))
    rows = sorted((r["first"], r["last"], r["file"]) for r in bounds.collect())
    return [r[0] for r in rows], [r[1] for r in rows], [r[2] for r in rows]


def _with_ranges(spark: SparkSession, path: str, ranges: DataFrame) -> DataFrame:
    """(file, content, ranges) of the files below ``path`` that ranges (file, offset, length) name.

    A file's ranges are as many as its members at most, which its size bounds.
    """
    by_file = ranges.groupBy("file").agg(F.collect_list(F.struct("offset", "length")).alias("ranges"))
    if ranges.count() <= SENT_RANGES:  # then files stay where they are read; beyond it they meet their ranges in a shuffle
        by_file = F.broadcast(by_file)
    return storage.read_blobs(spark, path).join(by_file, F.col("path") == F.col("file")).select("file", "content", "ranges")


def located(spark: SparkSession, index: str, urls: DataFrame) -> DataFrame:
    """(file, offset, length) of the records of all captures of ``urls`` (column url), each capture once.

    Distinct keys go in order, in batches, through the two levels: the key ranges of block files, then the directory
    rows of the file, then the lines of the block, each by binary search. A null or empty url stands for captures
    without a target, urls that the index lacks give nothing, and so does an empty table.
    """
    directory = spark.read.parquet(f"{index}/directory")
    firsts, lasts, names = _files_of_blocks(directory)

    def keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array([index_key(u) for u in batch.column(0).to_pylist()], pa.string())], ["key"])

    def files(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            held: dict[int, list[str]] = {}
            for key in batch.column(0).to_pylist():
                for at in _covering(firsts, lasts, key):
                    held.setdefault(at, []).append(key)
            yield pa.RecordBatch.from_arrays([pa.array([names[at] for at in held], pa.string()), pa.array(list(held.values()), pa.list_(pa.string()))], ["file", "keys"])

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                own = sorted((b["first_key"], b["last_key"], b["offset"], b["length"]) for b in row["blocks"])
                low, high, held = [b[0] for b in own], [b[1] for b in own], {}
                for key in row["keys"]:
                    for at in _covering(low, high, key):
                        held.setdefault(at, []).append(key)
                columns = [[row["file"]] * len(held), [own[at][2] for at in held], [own[at][3] for at in held], list(held.values())]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, [pa.string(), pa.int64(), pa.int64(), pa.list_(pa.string())])], ["file", "offset", "length", "keys"])

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for file, content, where in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2)):
                data, at = content.as_buffer(), [(r["offset"], r["length"]) for r in where.as_py()]
                parts = [data.slice(o, n).to_pybytes() for o, n in at]
                yield pa.RecordBatch.from_arrays([pa.array([file] * len(at), pa.string()), pa.array([o for o, _ in at], pa.int64()), pa.array(parts, pa.binary())], ["file", "offset", "block"])

    def records(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for block, wanted in zip(batch.column(0), batch.column(1).to_pylist()):
                lines = _block_lines(zlib.decompress(block.as_buffer(), 31))
                own = _keys(lines)
                for key in wanted:
                    found = (json.loads(x.split("\t", 1)[1]) for x in lines[bisect_left(own, key) : bisect_right(own, key)])
                    rows += [(x["file"], x["offset"], x["length"]) for x in found]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows) if rows else [()] * 3, [pa.string(), pa.int64(), pa.int64()])], ["file", "offset", "length"])

    distinct = storage.saved(urls.select("url").mapInArrow(keys, "key string").distinct(), "keys")
    ordered = distinct.repartitionByRange(max(int(spark.conf.get("spark.sql.shuffle.partitions")), 1), "key").sortWithinPartitions("key")
    by_file = directory.groupBy("file").agg(F.collect_list(F.struct("first_key", "last_key", "offset", "length")).alias("blocks"))
    asked = ordered.mapInArrow(files, "file string, keys array<string>").join(by_file, "file")
    asked = storage.saved(asked.mapInArrow(blocks, "file string, offset long, length long, keys array<string>"), "asked")
    parts = _with_ranges(spark, f"{index}/blocks", asked.select("file", "offset", "length").distinct())
    found = parts.mapInArrow(cut, "file string, offset long, block binary").join(asked, ["file", "offset"]).select("block", "keys")
    return found.mapInArrow(records, "file string, offset long, length long")


def read_range(spark: SparkSession, file: str, offset: int, length: int) -> bytes:
    """Bytes of a file by Spark's own file system layer, whatever store it is in."""
    jvm = spark.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(file)
    stream = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).open(path)
    try:
        stream.seek(offset)
        return bytes(stream.readNBytes(length))
    finally:
        stream.close()


class CaptureIndex:
    """Look-ups by URL: key ranges of block files in memory, a file's directory rows, blocks and records by range."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.directory = spark, spark.read.parquet(f"{path}/directory")
        self.firsts, self.lasts, self.files = _files_of_blocks(self.directory)

    def captures(self, url: str | None) -> list[dict]:
        """The index lines of a URL, in index order."""
        key, out = index_key(url), []
        for at in _covering(self.firsts, self.lasts, key):
            rows = self.directory.where((F.col("file") == self.files[at]) & (F.col("first_key") <= key) & (F.col("last_key") >= key))
            for block in rows.orderBy("offset").collect():
                lines = _block_lines(zlib.decompress(read_range(self.spark, block["file"], block["offset"], block["length"]), 31))
                keys = _keys(lines)
                out += [json.loads(x.split("\t", 1)[1]) for x in lines[bisect_left(keys, key) : bisect_right(keys, key)]]
        return out

    def read(self, line: dict) -> tuple[dict[str, str], bytes]:
        """(header fields, payload) of a capture; a revisit has no payload of its own."""
        fields, block = parsed(zlib.decompress(read_range(self.spark, line["file"], line["offset"], line["length"]), 31))
        return fields, block.partition(b"\r\n\r\n")[2]


def read_captures(spark: SparkSession, archives: str, index: str, urls: DataFrame) -> DataFrame:
    """All captures of ``urls`` (column url), looked up in the index and read by their ranges: page_id, url, payload_bytes,
    payload_digest, record_type, refers_to, payload.

    A response's length and digest are taken from the payload itself and held against its header; a revisit's come
    from its header. Nulls, unknown urls and empty tables as in ``located``.
    """
    found = _with_ranges(spark, archives, storage.saved(located(spark, index, urls), "ranges")).select("content", "ranges")
    schema = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary"
    kinds = [pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.binary()]
    names = [x.split()[0] for x in schema.split(", ")]

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for content, where in zip(batch.column(0), batch.column(1)):
                data, rows = content.as_buffer(), []
                for r in where.as_py():
                    fields, block = parsed(zlib.decompress(data.slice(r["offset"], r["length"]), 31))
                    http, _, payload = block.partition(b"\r\n\r\n")
                    n = int(http.rpartition(b"Content-Length:")[2])
                    digest = fields["WARC-Payload-Digest"].removeprefix("sha1:")
                    if fields["WARC-Type"] == "response" and (n, digest) != (len(payload), base64.b32encode(hashlib.sha1(payload).digest()).decode()):
                        raise ValueError(f"payload of {fields['WARC-Record-ID']} does not fit its header")
                    page, refers = fields["X-Page"], fields.get("X-Refers-To-Page")
                    rows.append((int(page) if page else None, fields.get("WARC-Target-URI"), n, digest, fields["WARC-Type"], int(refers) if refers else None, payload))
                    if len(rows) == 500:
                        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names)
                        rows = []
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names)

    return found.mapInArrow(read, schema)

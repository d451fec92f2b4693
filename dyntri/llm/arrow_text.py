"""Vectorised word work on Arrow text columns: no Python object per word."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

SPACE = bytes([9, 10, 11, 12, 13, 32])
#: Bytes looked at in one go; a longer text is a piece of its own.
PIECE_BYTES = 2_000_000


def text_pieces(column: pa.Array, most: int = PIECE_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, bytes, offsets) of consecutive rows; nulls count as empty texts."""
    column = pc.fill_null(column.cast(pa.large_string()), "")
    n = len(column)
    if not n:
        return
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + n + 1]
    data = np.frombuffer(column.buffers()[2] or b"", np.uint8)
    first = 0
    while first < n:
        end = max(first + 1, int(np.searchsorted(offsets, offsets[first] + most, "right")) - 1)
        own = offsets[first : end + 1]
        yield first, end, data[own[0] : own[-1]], own - own[0]
        first = end


def word_table(space: bytes = SPACE) -> np.ndarray:
    """256 flags: is the byte part of a word."""
    table = np.ones(256, bool)
    table[list(space)] = False
    return table


def word_spans(data: np.ndarray, offsets: np.ndarray, table: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(starts, ends, words of each row): maximal runs of word bytes, cut where rows end."""
    inside = table[data]
    if not len(data):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offsets) - 1, np.int64)
    before = np.empty_like(inside)
    before[0] = False
    before[1:] = inside[:-1]
    edges = offsets[:-1]
    before[edges[edges < len(data)]] = False
    starts = np.flatnonzero(inside & ~before)
    after = np.empty_like(inside)
    after[-1] = False
    after[:-1] = inside[1:]
    edges = offsets[1:]
    after[edges[edges > 0] - 1] = False
    ends = np.flatnonzero(inside & ~after) + 1
    return starts, ends, np.diff(np.searchsorted(starts, offsets))


def mixed(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor-shift and multiply, the public murmur3 one)."""
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


_STEP = np.uint64(0x9E3779B97F4A7C15)
_BYTE = mixed((np.arange(256, dtype=np.uint64) + np.uint64(1)) * _STEP) | np.uint64(1)


def byte_codes(table: np.ndarray, lower: bool = True) -> np.ndarray:
    """A random 64-bit number per byte, 0 between words; A-Z count as a-z."""
    codes = np.where(table, _BYTE, np.uint64(0))
    if lower:
        codes[65:91] = codes[97:123]
    return codes


def word_hashes(data: np.ndarray, starts: np.ndarray, codes: np.ndarray) -> np.ndarray:
    """A 64-bit hash per word: a polynomial in the bytes' codes, then mixed."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    place = np.arange(len(data), dtype=np.int64)
    place[starts[0] :] -= np.repeat(starts, np.diff(np.append(starts, len(data))))
    place[: starts[0]] = 0
    powers = np.cumprod(np.full(int(place.max()) + 1, _STEP, np.uint64), dtype=np.uint64)
    return mixed(np.add.reduceat(codes[data] * powers[place], starts))


_LOW = np.arange(256, dtype=np.uint8)
_LOW[65:91] += 32
_MASKS = np.array([(1 << 8 * k) - 1 for k in range(9)], np.uint64)


def lowered(data: np.ndarray) -> np.ndarray:
    """Bytes with A-Z as a-z, and 8 zeros behind them for :func:`blocks`."""
    out = np.zeros(len(data) + 8, np.uint8)
    np.take(_LOW, data, out=out[: len(data)])
    return out


def blocks(padded: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The first 8 bytes at most of each word as an integer; padded has 8 bytes more than the words."""
    every = np.ndarray((len(padded) - 7,), "<u8", padded, strides=(1,))
    return every[starts] & _MASKS[np.minimum(sizes, 8)]


def block_hashes(padded: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash per word, 8 bytes at a time; the bytes are taken as they are."""
    sizes = ends - starts
    out = mixed(blocks(padded, starts, sizes) ^ sizes.astype(np.uint64) * _STEP)
    left = np.flatnonzero(sizes > 8)
    at, size = starts[left] + 8, sizes[left] - 8
    while len(left):
        out[left] = mixed(out[left] * _STEP ^ blocks(padded, at, size))
        on = size > 8
        left, at, size = left[on], at[on] + 8, size[on] - 8
    return out


_AT = mixed(np.arange(1, 65, dtype=np.uint64) * np.uint64(0xD6E8FEB86659FD93)) | np.uint64(1)


def shingle_hashes(words: np.ndarray, size: int) -> np.ndarray:
    """Hashes of all windows of ``size`` words of one text; a shorter text that has words gives one, of them all."""
    if not len(words):
        return words
    size = min(size, len(words))
    n = len(words) - size + 1
    total = np.full(n, np.uint64(size * int(_STEP) % (1 << 64)))
    for k in range(size):
        total += words[k : k + n] * _AT[k]
    return mixed(total)


def cut_points(data: np.ndarray, table: np.ndarray, most: int) -> list[int]:
    """Ends of consecutive stretches of one text, about ``most`` bytes each, none inside a word; the last is the text's end."""
    out, at = [], 0
    while len(data) - at > most:
        at += most
        while at < len(data) and table[data[at]]:
            gap = np.flatnonzero(~table[data[at : at + 4096]])
            at += int(gap[0]) if len(gap) else min(4096, len(data) - at)
        out.append(at)
    return [*out, len(data)]


class HashIndex:
    """64-bit hashes to small integers: open addressing over arrays that grow, whole arrays of hashes at a time."""

    def __init__(self, room: int):
        self.n = 0
        self._room(room)

    def _room(self, room: int) -> None:
        size = 1 << max(10, (2 * room - 1).bit_length())
        self.keys, self.values, self.mask = np.zeros(size, np.uint64), np.zeros(size, np.int32), np.uint64(size - 1)

    def find(self, hashes: np.ndarray) -> np.ndarray:
        """The values, -1 where a hash is unknown."""
        hashes = np.where(hashes == 0, np.uint64(1), hashes)
        slot = (hashes & self.mask).astype(np.int64)
        out = np.full(len(hashes), -1, np.int64)
        rows = np.arange(len(hashes))
        while len(rows):
            there = self.keys[slot]
            hit = there == hashes
            out[rows[hit]] = self.values[slot[hit]]
            on = ~hit & (there != 0)
            rows, hashes, slot = rows[on], hashes[on], (slot[on] + 1) & int(self.mask)
        return out

    def add(self, hashes: np.ndarray, values: np.ndarray) -> None:
        """hashes: distinct and not yet known."""
        if 4 * (self.n + len(hashes)) > 3 * len(self.keys):
            old, there = self.keys != 0, self.values
            keys, there = self.keys[old], there[old]
            self._room(2 * (self.n + len(hashes)))
            self._put(keys, there)
        self.n += len(hashes)
        self._put(np.where(hashes == 0, np.uint64(1), hashes), values)

    def _put(self, hashes: np.ndarray, values: np.ndarray) -> None:
        slot = (hashes & self.mask).astype(np.int64)
        while len(hashes):
            free = self.keys[slot] == 0
            self.keys[slot[free]] = hashes[free]  # of several, the last stays
            own = free & (self.keys[slot] == hashes)
            self.values[slot[own]] = values[own]
            hashes, values, slot = hashes[~own], values[~own], (slot[~own] + 1) & int(self.mask)

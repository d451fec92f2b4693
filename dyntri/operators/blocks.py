"""Exact triangle counts in blocks of the adjacency matrix: what is shuffled follows the edges, not the wedges.

Vertices have one of p colours. Edges between two colours are packed into pieces, and each triple of colours gets the pieces
of its three pairs, so an edge has p copies of a few bytes and each triangle is counted in one task. p grows with the root
of the edges, which keeps a task's share at BLOCK_EDGES on average.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Edges that one triple of colours gets on average.
BLOCK_EDGES = 8_000_000
#: Edges below which all is one block, and the least number of colours above.
SMALL, LEAST = 20_000, 4
#: Edges that are packed at a time, wedges looked up at a time, and bytes of a dense strip.
PACKED, WEDGES, STRIP = 1 << 20, 1 << 21, 1 << 25
#: What a looked-up wedge costs, in words of a dense row.
WEDGE_COST = 10
_ODD = np.uint64(0x9E3779B97F4A7C15)

#: Edges from one class of vertices to another, by place: (from, to).
Side = tuple[np.ndarray, np.ndarray]


def colours(edges: int) -> int:
    return 1 if edges < SMALL else max(LEAST, math.ceil(math.sqrt(6 * edges / BLOCK_EDGES)))


def packed(x: np.ndarray, y: np.ndarray) -> bytes:
    """Edges sorted by x and y, as differences, bytes of a rank together."""
    dx = np.diff(x, prepend=0)
    same = np.r_[False, x[1:] == x[:-1]]
    dy = np.where(same, np.diff(y, prepend=0), y)
    raw = np.ascontiguousarray(np.concatenate([dx, dy]).view(np.uint8).reshape(-1, 8).T).tobytes()
    return len(x).to_bytes(8, "little") + pa.compress(raw, codec="zstd", asbytes=True)


def unpacked(piece: bytes) -> tuple[np.ndarray, np.ndarray]:
    n = int.from_bytes(piece[:8], "little")
    raw = np.frombuffer(pa.decompress(piece[8:], decompressed_size=16 * n, codec="zstd", asbytes=True), np.uint8)
    dx, dy = np.ascontiguousarray(raw.reshape(8, -1).T).reshape(-1).view(np.int64).reshape(2, n)
    first = np.flatnonzero(np.r_[True, dx[1:] != 0])
    total = np.cumsum(dy)
    base = total[first] - dy[first]
    return np.cumsum(dx), total - np.repeat(base, np.diff(np.r_[first, n]))


def _pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    def flush(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(held)
        i, j, x, y = (np.array(table.column(c), np.int64) for c in ("i", "j", "x", "y"))
        order = np.lexsort((y, x, j, i))
        i, j, x, y = i[order], j[order], x[order], y[order]
        at = np.r_[np.flatnonzero(np.r_[True, (i[1:] != i[:-1]) | (j[1:] != j[:-1])]), len(i)]
        for a, b in zip(at[:-1], at[1:]):
            yield pa.RecordBatch.from_pylist([{"i": int(i[a]), "j": int(j[a]), "piece": packed(x[a:b], y[a:b])}], pa.schema([("i", pa.int32()), ("j", pa.int32()), ("piece", pa.binary())]))

    held, n = [], 0
    for batch in batches:
        held, n = [*held, batch], n + batch.num_rows
        if n >= PACKED:
            yield from flush(held)
            held, n = [], 0
    if n:
        yield from flush(held)


def _rows(side: Side, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(first place of each row in the second array, columns in order) of a side."""
    order = np.lexsort((side[1], side[0]))
    return np.r_[0, np.cumsum(np.bincount(side[0], minlength=n))], side[1][order]


class _Lookup:
    """Whether (row, column) is an edge; most that are none are told by one byte."""

    def __init__(self, rows: tuple[np.ndarray, np.ndarray], width: int) -> None:
        start, cols = rows
        self.width = width
        self.keys = np.repeat(np.arange(len(start) - 1), np.diff(start)) * width + cols
        self.shift = np.uint64(64 - max(10, (8 * len(self.keys)).bit_length()))
        self.seen = np.zeros(1 << int(64 - self.shift), bool)
        self.seen[self._slot(self.keys)] = True

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return (keys.astype(np.uint64) * _ODD) >> self.shift

    def __call__(self, row: np.ndarray, col: np.ndarray) -> np.ndarray:
        """Places of the pairs that are edges."""
        key = row * self.width + col
        some = np.flatnonzero(self.seen[self._slot(key)])
        at = np.searchsorted(self.keys, key[some])
        return some[self.keys[np.minimum(at, len(self.keys) - 1)] == key[some]]


class _Triple:
    """Triangles (x, y, z) with (x, y) in the base side, (x, z) and (y, z) in the others."""

    def __init__(self, base: Side, xz: Side, yz: Side, sizes: tuple[int, int, int]) -> None:
        self.nx, self.ny, self.nz = sizes
        self.x_rows, self.y_rows = _rows(xz, self.nx), _rows(yz, self.ny)
        dx, dy = np.diff(self.x_rows[0]), np.diff(self.y_rows[0])
        on = (dx[base[0]] > 0) & (dy[base[1]] > 0)
        self.x, self.y = base[0][on], base[1][on]
        self.by_x = dx[self.x] <= dy[self.y]
        self.wedges = np.minimum(dx[self.x], dy[self.y])
        self.sparse_cost = WEDGE_COST * int(self.wedges.sum())
        self.dense_cost = (len(self.x) + self.nx + self.ny) * (self.nz // 64 + 1)

    @property
    def cost(self) -> int:
        return min(self.sparse_cost, self.dense_cost)

    def found(self) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """All triangles, by looking up the wedges of the end with fewer."""
        for on, rows, other in ((self.by_x, self.x_rows, self.y_rows), (~self.by_x, self.y_rows, self.x_rows)):
            place = np.flatnonzero(on)
            if not len(place):
                continue
            lookup = _Lookup(other, self.nz)
            near, far = (self.x, self.y) if rows is self.x_rows else (self.y, self.x)
            ends = np.cumsum(self.wedges[place])
            for some in np.split(place, np.unique(np.searchsorted(ends, np.arange(WEDGES, ends[-1], WEDGES)))):
                if not len(some):
                    continue
                n = self.wedges[some]
                z = rows[1][np.repeat(rows[0][near[some]] - np.cumsum(n) + n, n) + np.arange(n.sum())]
                edge = np.repeat(some, n)
                hit = lookup(far[edge], z)
                yield self.x[edge[hit]], self.y[edge[hit]], z[hit]

    def common(self) -> np.ndarray:
        """Triangles of each base edge, by rows of bits, in strips of columns."""
        out = np.zeros(len(self.x), np.int64)
        width = max(64, STRIP // (self.nx + self.ny) // 64 * 64)
        for low in range(0, self.nz, width):
            bits = []
            for (start, cols), n in ((self.x_rows, self.nx), (self.y_rows, self.ny)):
                row = np.repeat(np.arange(n), np.diff(start))
                on = (cols >= low) & (cols < low + width)
                strip = np.zeros((n, width), bool)
                strip[row[on], cols[on] - low] = True
                bits.append(np.packbits(strip, axis=1).view(np.uint64))
            step = max(1, (1 << 20) * 64 // width)
            for a in range(0, len(out), step):
                out[a : a + step] += np.bitwise_count(bits[0][self.x[a : a + step]] & bits[1][self.y[a : a + step]]).sum(axis=1, dtype=np.int64)
        return out


def _flip(side: Side) -> Side:
    return side[1], side[0]


def count(ab: Side, ac: Side, bc: Side, sizes: tuple[int, int, int], local: bool) -> tuple[int, list[np.ndarray]]:
    """(triangles with one edge of each side, and with ``local`` those of each a, b and c)."""
    na, nb, nc = sizes
    views = [((0, 1, 2), _Triple(ab, ac, bc, (na, nb, nc))), ((0, 2, 1), _Triple(ac, ab, _flip(bc), (na, nc, nb))), ((1, 2, 0), _Triple(bc, _flip(ab), _flip(ac), (nb, nc, na)))]
    roles, best = min(views, key=lambda v: v[1].cost)
    total, each = 0, [np.zeros(n, np.int64) for n in sizes]
    if best.sparse_cost <= best.dense_cost:
        for xyz in best.found():
            total += len(xyz[0])
            for role, place in zip(roles, xyz if local else ()):
                each[role] += np.bincount(place, minlength=sizes[role])
        return total, each
    n = best.common()
    # sums of integers below 2^53, so the weights' doubles are exact
    if local:
        for role, place in zip(roles, (best.x, best.y)):
            each[role] += np.bincount(place, n, sizes[role]).astype(np.int64)
        last, other = roles[2], next(v for v in views if v[0] != roles and roles[2] in v[0][:2])
        side = other[0].index(last)
        each[last] += np.bincount((other[1].x, other[1].y)[side], other[1].common(), sizes[last]).astype(np.int64)
    return int(n.sum()), each


def _counted(table: pa.Table, p: int, local: bool) -> pa.Table:
    t = table.column("t")[0].as_py()
    i, j, k = t // (p * p), t // p % p, t % p
    pieces: dict[tuple[int, int], list] = {}
    for a, b, piece in zip(*(table.column(c).to_pylist() for c in ("i", "j", "piece"))):
        pieces.setdefault((a, b), []).append(unpacked(piece))

    def side(a: int, b: int) -> Side:
        own = pieces.get((a, b), [(np.zeros(0, np.int64),) * 2])
        return np.concatenate([x for x, _ in own]), np.concatenate([y for _, y in own])

    # with two vertices of one colour, these are a < b; edges of one colour lead from the smaller vertex to the larger
    if j == k and i != j:
        ab, ac, bc = side(j, j), _flip(side(i, j)), _flip(side(i, j))
    else:
        ab, ac, bc = side(i, j), side(i, k), side(j, k)
    ids = [np.unique(np.concatenate(x)) for x in ((ab[0], ac[0]), (ab[1], bc[0]), (ac[1], bc[1]))]
    place = lambda s, x, y: (np.searchsorted(ids[x], s[0]), np.searchsorted(ids[y], s[1]))
    total, each = count(place(ab, 0, 1), place(ac, 0, 2), place(bc, 1, 2), tuple(map(len, ids)), local)
    if not local:
        return pa.table({"triangles": pa.array([total], pa.int64())})
    node, n = np.concatenate(ids), np.concatenate(each)
    return pa.table({"node": pa.array(node[n > 0], pa.int64()), "triangles": pa.array(n[n > 0], pa.int64())})


def counted(edges: DataFrame, local: bool = False) -> DataFrame:
    """(triangles), or (node, triangles) of vertices with any, once for each triple of colours: to be summed."""
    p = colours(edges.count())
    colour = lambda c: F.pmod(F.xxhash64(F.col(c).cast("long")), F.lit(p)).cast("int")
    rows = edges.select(F.least("u", "v").cast("long").alias("u"), F.greatest("u", "v").cast("long").alias("v")).select("u", "v", colour("u").alias("c_u"), colour("v").alias("c_v"))
    turn = F.col("c_v") < F.col("c_u")
    ends = [F.when(turn, F.col(b)).otherwise(F.col(a)).alias(name) for a, b, name in (("c_u", "c_v", "i"), ("c_v", "c_u", "j"), ("u", "v", "x"), ("v", "u", "y"))]
    pieces = rows.select(*ends).mapInArrow(_pack, "i int, j int, piece binary")
    met = pieces.select("i", "j", "piece", F.explode(F.sequence(F.lit(0), F.lit(p - 1))).alias("k"))
    three = F.array_sort(F.array("i", "j", "k"))
    met = met.select(((three[0].cast("long") * p + three[1]) * p + three[2]).alias("t"), "i", "j", "piece")
    return met.groupBy("t").applyInArrow(lambda table: _counted(table, p, local), "node long, triangles long" if local else "triangles long")

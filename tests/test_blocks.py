"""Block-wise counts against matrix products, by both ways of a task, and without wedges in the plan."""

import itertools

import numpy as np
import pyarrow as pa
import pytest

from dyntri.operators import blocks, exact
from tests.test_counting_size import _join_rows


def _graph(n, share, seed=0):
    rng = np.random.default_rng(seed)
    m = np.triu(rng.random((n, n)) < share, 1)
    ids = rng.permutation(10**6)[:n].astype(np.int64) - 500_000
    a = (m | m.T).astype(int)
    return ids, [tuple(sorted((int(ids[u]), int(ids[v])))) for u, v in np.argwhere(m)], int(np.trace(a @ a @ a)) // 6, dict(zip(ids.tolist(), (np.diag(a @ a @ a) // 2).tolist()))


def test_pieces_come_back():
    x, y = np.array([-5, -5, 0, 0, 7], np.int64), np.array([3, 2**40, -9, 4, 4], np.int64)
    got = blocks.unpacked(blocks.packed(x, y))
    assert got[0].tolist() == x.tolist() and got[1].tolist() == y.tolist()


@pytest.mark.parametrize("p,cost,share", list(itertools.product((1, 2, 5), (0, 10**9), (0.1, 0.8))))
def test_all_triples_of_colours_give_each_triangle_once(monkeypatch, p, cost, share):
    monkeypatch.setattr(blocks, "WEDGE_COST", cost)
    monkeypatch.setattr(blocks, "WEDGES", 50)
    ids, edges, total, local = _graph(50, share)
    pieces = {}
    for u, v in edges:
        i, j = abs(u) % p, abs(v) % p
        pieces.setdefault((min(i, j), max(i, j)), []).append((v, u) if j < i else (u, v))
    got, each = 0, dict.fromkeys(ids.tolist(), 0)
    for i, j, k in itertools.combinations_with_replacement(range(p), 3):
        own = [(q, blocks.packed(*np.array(sorted(pieces[q]), np.int64).T)) for q in {(i, j), (i, k), (j, k), (i, i), (k, k)} if q in pieces and (q[0] != q[1] or [i, j, k].count(q[0]) > 1)]
        if own:
            table = pa.table({"t": [(i * p + j) * p + k] * len(own), "i": [q[0] for q, _ in own], "j": [q[1] for q, _ in own], "piece": pa.array([x for _, x in own], pa.binary())})
            got += blocks._counted(table, p, False).column(0)[0].as_py()
            for r in blocks._counted(table, p, True).to_pylist():
                each[r["node"]] += r["triangles"]
    assert got == total and each == local


def test_exact_counts_bring_no_wedges(spark, monkeypatch):
    monkeypatch.setattr(blocks, "SMALL", 1)
    ids, edges, total, local = _graph(60, 0.7)
    s = spark.createDataFrame([(i, u, v) for i, (u, v) in enumerate(edges)], "seq long, u long, v long")
    counts = exact.exact_global(s)
    assert _join_rows(counts) < len(edges)  # all wedges before
    assert counts.first()[0] == total
    assert {r.node: r.triangles for r in exact.exact_local(s).collect()} == local

"""The kernel of the reservoirs on many groups."""

import random

import pyarrow as pa

from dyntri.operators import sampling


def _by_sorting(rows, k):
    """(group, seq, exit_seq) by sorting each prefix of a group."""
    out = []
    for g in sorted({r[0] for r in rows}):
        own, held = [r for r in rows if r[0] == g], []
        for _, seq, key in own:
            new = sorted([*held, (key, seq)])[:k]
            out += [(g, x[1], seq) for x in held if x not in new]
            held = new
            if (key, seq) not in held:
                continue
        out += [(g, x[1], None) for x in held]
    return sorted(out, key=str)


def test_groups_over_batches():
    draw = random.Random(5)
    rows = [(g, g * 100 + i, draw.randrange(10**6)) for g in range(40) for i in range(draw.randrange(1, 60))]
    for k in (2, 7, 100):
        whole = pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows)], ["shard", "seq", "key"])
        batches = [whole.slice(i, 37) for i in range(0, len(whole), 37)]
        got = [tuple(r.values()) for b in sampling._reservoirs(iter(batches), k, 1, True) for r in b.to_pylist()]
        assert sorted(got, key=str) == _by_sorting(rows, k)
        entered = {r["seq"] for b in sampling._reservoirs(iter(batches), k, 1, False) for r in b.to_pylist()}
        assert entered == {s for _, s, _ in got}
    assert list(sampling._reservoirs(iter([]), 2, 1, True)) == []


def test_residency_of_many_sets_takes_no_call_for_each(spark, monkeypatch):
    from pyspark.sql import GroupedData

    def refuse(*a, **b):
        raise AssertionError("a call for each group")

    kind = type(spark.range(1).groupBy("id"))
    for one in {kind, GroupedData}:
        monkeypatch.setattr(one, "applyInPandas", refuse, raising=False)
    rows = [(0, i // 10, i, i, i + 1, (i * 7919) % 1009) for i in range(400)]
    stored = spark.createDataFrame(rows, "run int, segment int, seq long, u long, v long, key long")
    got = sampling.reservoir_residency(stored, 3, ["run", "segment"], ["u", "v"], 10).collect()
    assert sorted(((r.segment, r.enter_seq, r.exit_seq) for r in got), key=str) == _by_sorting([(r[1], r[2], r[5]) for r in rows], 3)

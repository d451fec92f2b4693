"""Estimates of an experiment from closings that are listed once: the hits are those of each method alone."""

import pytest
from pyspark.sql import functions as F

from dyntri.operators import exact, routing, sampling
from dyntri.operators.streams import with_deletions
from dyntri.plans import methods, workloads
from dyntri.sources import shared


@pytest.fixture(scope="module")
def events(spark):
    rows = spark.range(400).select((F.col("id") * 7919 % 30).alias("a"), (F.col("id") * 104729 % 31).alias("b")).where("a <> b").select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v")).distinct()
    ordered = rows.toPandas().sort_values(["u", "v"]).sample(frac=1, random_state=3).reset_index(drop=True)
    return shared.cut(spark.createDataFrame([(i, None, int(u), int(v), 1) for i, (u, v) in enumerate(ordered.itertuples(index=False))], "seq long, ts timestamp, u long, v long, sign byte"))


@pytest.fixture(scope="module")
def signed(events):
    """Deletions, and then some of the deleted edges again."""
    signed = with_deletions(events, 0.4)
    last = signed.agg(F.max("seq")).first()[0]
    again = signed.where("sign = -1 and seq % 2 = 0").select((F.col("seq") + last + 1).alias("seq"), "ts", "u", "v", F.lit(1).cast("byte").alias("sign"))
    return shared.cut(signed.unionByName(again))


def _hits(result, seq=True):
    rows = result.hits.select("run", "shard", "seq", "sign", "u", "v", "c", "seg_a", "seg_b", "kind", "num").collect()
    assert rows
    return sorted(map(str, rows))


@pytest.mark.parametrize("large", [False, True])
def test_hits_of_insertions(spark, events, monkeypatch, large):
    monkeypatch.setattr(methods, "settled", lambda spark: None)
    closed = shared.cut(exact.closings(events))
    assert closed.count() == exact.exact_global(events).first()[0]
    with shared.passing(spark), monkeypatch.context() as m:
        m.setattr(shared, "LARGE", 1 if large else shared.LARGE)
        three, one = methods.insertion_layout(events, closed, 3), methods.insertion_layout(events, closed, 1)
        got = [_hits(x) for x in (
            methods.adaptive_triangles(events, 3, 10, 0.3, runs=2, layout=three), methods.adaptive_triangles(events, 3, 10, 0.1, memory=30, runs=2, layout=three),
            methods.sharded_triangles(events, 3, 40, runs=2, layout=three), methods.solo_reservoir_triangles(events, 80, runs=2, layout=one), methods.solo_coin_triangles(events, 0.4, runs=2, closed=closed),
        )]
    want = [_hits(x) for x in (
        methods.adaptive_triangles(events, 3, 10, 0.3, runs=2), methods.adaptive_triangles(events, 3, 10, 0.1, memory=30, runs=2), methods.sharded_triangles(events, 3, 40, runs=2),
        methods.solo_reservoir_triangles(events, 80, runs=2), methods.solo_coin_triangles(events, 0.4, runs=2),
    )]
    assert got == want


def test_hits_with_deletions(signed):
    closed = shared.cut(exact.closings(signed))
    assert closed.agg(F.sum("sign")).first()[0] == exact.exact_dynamic(signed).first()[0]
    three, one = methods.slot_layout(signed, closed, 3), methods.slot_layout(signed, closed, 1)
    assert _hits(methods.dynamic_triangles(signed, 3, 40, runs=2, layout=three)) == _hits(methods.dynamic_triangles(signed, 3, 40, runs=2))
    assert _hits(methods.solo_paired_triangles(signed, 60, runs=2, layout=one)) == _hits(methods.solo_paired_triangles(signed, 60, runs=2))
    assert _hits(methods.solo_coin_dynamic(signed, 0.4, runs=2, closed=closed)) == _hits(methods.solo_coin_dynamic(signed, 0.4, runs=2))
    assert methods.solo_paired_conditional(signed, 60, runs=2, layout=one).collect() == methods.solo_paired_conditional(signed, 60, runs=2).collect()


def test_slots_by_kernel(signed):
    routed = routing.route_store(signed, 3)
    assert sorted(sampling.assign_slots(routed, most=1000).collect()) == sorted(sampling.assign_slots(routed).collect())


def test_no_cell_joins_wedges(events, monkeypatch):
    monkeypatch.setattr(workloads.methods.counting, "closing_hits", None)
    rows = workloads.accuracy(events, "small", shares=(0.1,), n_shards=3, runs=2).collect()
    assert {r.method for r in rows} == {"adaptive", "sharded", "solo_reservoir", "solo_coin"}


def test_long_groups_as_arrays(monkeypatch):
    import random

    import pyarrow as pa

    draw = random.Random(3)
    rows = [(g, i, draw.randrange(10**6)) for g in range(6) for i in range(draw.randrange(150, 700))]
    whole = pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows)], ["shard", "seq", "key"])
    for k in (2, 30, 1000):
        for ends in (True, False):
            got = []
            for least in (1, 10**9):
                monkeypatch.setattr(sampling, "LEAST_ROWS", least)
                batches = (whole.slice(i, 500) for i in range(0, len(whole), 500))
                got.append(sorted((tuple(r.values()) for b in sampling._reservoirs(batches, k, 1, ends) for r in b.to_pylist()), key=str))
            assert got[0] == got[1] and got[0]

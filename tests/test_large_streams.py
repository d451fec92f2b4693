"""Streams whose runs go one by one, and tables that go with the step that made them."""

import os

import pytest
from pyspark.sql import functions as F

from dyntri.operators.streams import with_deletions
from dyntri.plans import methods, workloads
from dyntri.sources import shared


@pytest.fixture(scope="module")
def events(spark):
    rows = spark.range(400).select((F.col("id") * 7919 % 30).alias("a"), (F.col("id") * 104729 % 31).alias("b")).where("a <> b").select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v")).distinct()
    ordered = rows.toPandas().sort_values(["u", "v"]).sample(frac=1, random_state=3).reset_index(drop=True)
    return spark.createDataFrame([(i, None, int(u), int(v), 1) for i, (u, v) in enumerate(ordered.itertuples(index=False))], "seq long, ts timestamp, u long, v long, sign byte")


def _hits(result):
    return sorted(map(str, result.hits.select("run", "shard", "seq", "u", "v", "c", "kind", "num").collect()))


def test_runs_one_by_one_give_the_same(spark, events, monkeypatch):
    signed = shared.cut(with_deletions(events, 0.2))
    makes = [lambda: methods.adaptive_triangles(events, 2, 20, 0.2, runs=2), lambda: methods.dynamic_triangles(signed, 2, 20, runs=2)]
    monkeypatch.setattr(methods, "settled", lambda spark: None)
    for make in makes:
        together = _hits(make())
        assert together
        with shared.passing(spark):
            with monkeypatch.context() as m:
                m.setattr(shared, "LARGE", 1)
                one_by_one = _hits(make())
        assert one_by_one == together


def test_an_experiment_leaves_no_table_and_holds_one_cell(spark, events, monkeypatch):
    monkeypatch.setattr(shared, "LARGE", 1)
    monkeypatch.setattr(workloads, "settled", lambda spark: None)
    folder = shared._shared(spark).removeprefix("file:")
    tables = lambda: {x for x in os.listdir(folder) if x.startswith("cut-")}
    held = []
    row = workloads._row

    def seen(*args):
        before = tables()
        out = row(*args)
        held.append((len(before), tables() == before))
        return out

    monkeypatch.setattr(workloads, "_row", seen)
    with shared.passing(spark):
        stream = shared.cut(events)
        cells = [("coin", f"q={q}", lambda q=q: shared.cut(methods.solo_coin_triangles(stream, q).global_)) for q in (0.5, 0.6)]
        truth = spark.createDataFrame([(40,)], "triangles long")
        got = workloads._table("small", cells, stream, truth, None, 1).collect()
    assert len(got) == 2 and not tables()
    assert held == [(1, True), (1, True)]


def test_a_budget_of_a_chunk_goes_without_the_chunk_step(spark):
    from dyntri.operators import sampling

    rows = spark.range(500).select(F.lit(0).alias("run"), "id", F.col("id").alias("seq"), (F.col("id") * 7919 % 503).alias("key"))
    plan = lambda k: sampling.reservoir_residency(rows, k, ["run"], ["id"])._jdf.queryExecution().optimizedPlan().toString().count("MapInArrow")
    assert plan(sampling.CHUNK - 1) == 2 and plan(sampling.CHUNK) == 1

"""Counting meets no more rows than the smaller end of each event or edge brings."""

from dyntri.operators import sampling
from dyntri.plans import methods


def _stream(spark, pairs):
    rows = [(i, None, u, v, 1) for i, (u, v) in enumerate(pairs)]
    return spark.createDataFrame(rows, "seq long, ts timestamp, u long, v long, sign byte")


def _join_rows(df):
    """Rows that the joins of an executed plan gave out."""
    df.collect()

    def walk(plan):
        name = plan.nodeName()
        if name == "AdaptiveSparkPlan":
            return walk(plan.executedPlan())
        if "QueryStage" in name:
            return walk(plan.plan())
        own = plan.metrics().get("numOutputRows") if "Join" in name else None
        return (own.get().value() if own is not None and own.isDefined() else 0) + sum(walk(plan.children().apply(i)) for i in range(plan.children().size()))

    return walk(df._jdf.queryExecution().executedPlan())


def test_a_hub_is_not_multiplied_by_its_own_events(spark):
    n = 1000
    events = _stream(spark, [(0, v) for v in range(1, n + 1)] + [(1, 2)])
    hits = methods.sharded_triangles(events, 1, 10**4).hits.select("seq", "u", "v", "c")
    assert _join_rows(hits) < 20 * n  # n * n / 2 rows before
    assert [tuple(r) for r in hits.collect()] == [(n, 1, 2, 0)]


def test_segments_stay_with_their_ends(spark):
    # the wedge's edges lie in different sets, and the event's ends differ in degree both ways
    pairs = [(1, 9), (5, 9), (1, 2), (1, 3), (1, 5), (6, 7), (6, 8), (7, 8)]
    result = methods.adaptive_triangles(_stream(spark, pairs), 1, 2, 1.0)
    segment = {(r.u, r.v): r.segment for r in result.residency.collect()}
    rows = result.hits.select("u", "v", "c", "seg_a", "seg_b").collect()
    assert {(r.u, r.v, r.c) for r in rows} == {(1, 5, 9), (7, 8, 6)}
    for r in rows:
        assert r.seg_a == segment[tuple(sorted((r.u, r.c)))] and r.seg_b == segment[tuple(sorted((r.v, r.c)))]


def test_short_sets_go_without_passes_that_take_nothing_away(spark, monkeypatch):
    events = _stream(spark, [(u, v) for u in range(12) for v in range(u + 1, 12)])
    rows = lambda: sorted(map(tuple, methods.adaptive_triangles(events, 2, 4, 0.2).residency.collect()), key=str)
    want = rows()
    monkeypatch.setattr(sampling, "candidates", lambda *_: 1 / 0)
    assert rows() == want
    monkeypatch.undo()
    monkeypatch.setattr(sampling, "FEW", 0)
    monkeypatch.setattr(sampling, "CHUNK", 8)
    assert rows() == want

"""Worked examples, exact expectations by enumeration, and agreement of the plans with state machines and SQL."""

import itertools
from fractions import Fraction

import duckdb
import pytest
from pyspark.sql import functions as F

from dyntri import queries
from dyntri.functions.weights import seal_point
from dyntri.operators import counting, exact, replay, routing, sampling, streams
from dyntri.operators.streams import canonical_edges, live_edges, validated, with_deletions
from dyntri.plans import methods
from dyntri.sources import graphs
from dyntri.sources.shared import cut

SF = "/root/testdata/sf0.001"
K4 = [(0, 1), (1, 2), (2, 3), (0, 3), (0, 2), (1, 3)]
SIGNED = [(0, 1, 1), (1, 2, 1), (2, 3, 1), (0, 3, 1), (1, 2, -1), (0, 2, 1), (1, 3, 1), (1, 2, 1), (0, 3, -1), (2, 4, 1), (0, 3, 1)]


def stream(spark, events):
    rows = [(i, *min((e[:2], e[1::-1])), e[2] if len(e) > 2 else 1) for i, e in enumerate(events)]
    return spark.createDataFrame(rows, "seq long, u long, v long, sign byte")


def one(df):
    return df.first()[0]


@pytest.mark.parametrize("events,count", [([], 0), ([(1, 2)], 0), ([(1, 2), (2, 3), (1, 3)], 1), (K4, 4), (list(itertools.combinations(range(8), 2)), 56), ([(a, b + 9) for a in range(4) for b in range(4)], 0)])
def test_exact_counts_and_ample_budgets(spark, events, count):
    s = stream(spark, events)
    assert one(exact.exact_global(s)) == count
    assert one(exact.exact_dynamic(s)) == count
    if events:
        for w in (1, 3):
            assert methods.adaptive_triangles(s, w, 100).global_.first().est == count
            assert methods.dynamic_triangles(s, w, 100).global_.first().est == count


def test_local_counts(spark):
    assert {r.triangles for r in exact.exact_local(stream(spark, K4)).collect()} == {3}
    got = methods.adaptive_triangles(stream(spark, K4), 3, 50).local_.collect()
    assert {r.est for r in got} == {3.0} and len(got) == 4


@pytest.mark.parametrize("k", [2, 3, 4])
def test_reservoir_is_unbiased_by_enumeration(monkeypatch, k):
    """Over all orders of keys, the mean of a fixed reservoir's estimate is the truth exactly."""
    total, n = Fraction(0), 0
    for keys in itertools.permutations(range(6)):
        monkeypatch.setattr(replay, "key_of", lambda seed, run, shard, seq, u, v, keys=keys: keys[seq])
        shard = replay.AdaptiveShard(0, k, 0.5, max_sets=1)
        for seq, (u, v) in enumerate(K4):
            shard.event(seq, u, v, 1, True)
        total += Fraction(shard.total, k * k * (k - 1))
        n += 1
    assert total / n == 4


@pytest.mark.parametrize("k,floor", [(2, 1.0), (2, 0.67), (3, 1.0), (2, 0.5), (3, 0.75), (3, 0.6)])
def test_adaptive_pool_is_unbiased_by_enumeration(monkeypatch, k, floor):
    total, n = Fraction(0), 0
    for keys in itertools.permutations(range(6)):
        monkeypatch.setattr(replay, "key_of", lambda seed, run, shard, seq, u, v, keys=keys: keys[seq])
        shard = replay.AdaptiveShard(0, k, floor)
        for seq, (u, v) in enumerate(K4):
            shard.event(seq, u, v, 1, True)
        total += Fraction(shard.total, k * k * (k - 1))
        n += 1
    assert total / n == 4


@pytest.mark.parametrize("k", [2, 3])
def test_random_pairing_is_unbiased_by_enumeration(k):
    """All outcomes of the draws with their probabilities."""

    class Branching(replay.PairedShard):
        def __init__(self, script):
            super().__init__(0, k)
            self.script, self.used, self.p = script, [], Fraction(1)

        def _choose(self, weights):
            at = self.script[len(self.used)] if len(self.used) < len(self.script) else 0
            self.used.append((at, len(weights)))
            self.p *= weights[at]
            return at

        def _chance(self, part, whole):
            return self._choose([Fraction(part, whole), 1 - Fraction(part, whole)]) == 0

        def _pick(self, n):
            return self._choose([Fraction(1, n)] * n)

    mean, mass, script = Fraction(0), Fraction(0), []
    while True:
        shard = Branching(script)
        for seq, (u, v, sign) in enumerate(SIGNED):
            shard.event(seq, u, v, sign, True)
        mean += shard.p * Fraction(shard.total, k * (k - 1))
        mass += shard.p
        used = shard.used
        while used and used[-1][0] == used[-1][1] - 1:
            used.pop()
        if not used:
            break
        script = [a for a, _ in used[:-1]] + [used[-1][0] + 1]
    assert mass == 1 and mean == 4


def test_each_triangle_once_at_its_counting_shard(spark):
    events = cut(graphs.user_handoff(spark, SF))
    for w in (3, 7):
        hits = methods.sharded_triangles(events, w, 10**6).hits
        assert hits.groupBy("seq", "c").count().where("count > 1").isEmpty()
        assert hits.count() == 455
    copies = routing.route_store(events, 5).groupBy("seq").count().agg(F.max("count")).first()[0]
    assert copies <= 2


def test_relational_plan_equals_state_machines(spark):
    events = cut(graphs.customer_overlap(spark, SF))
    for k, floor in ((20, 0.2), (15, 0.4)):
        cols = ["shard", "seq", "u", "v", "c", "kind", "num"]
        a = methods.adaptive_triangles(events, 3, k, floor).hits.select(cols)
        b = replay.adaptive_replay(events, 3, k, floor).select(cols)
        assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty() and not a.isEmpty()


def test_deletions(spark):
    events = cut(graphs.user_handoff(spark, SF))
    signed = cut(with_deletions(events, 0.4))
    assert signed.where("sign = -1").count() == int(0.4 * 105)
    assert validated(signed)[1].isEmpty()
    truth = one(exact.exact_global(live_edges(signed)))
    assert one(exact.exact_dynamic(signed)) == truth
    for pairing in ("queue", "random"):
        assert methods.dynamic_triangles(signed, 3, 1000, pairing=pairing).global_.first().est == truth
    runs = methods.dynamic_triangles(signed, 2, 30, runs=60).global_.toPandas().est
    assert abs(runs.mean() - truth) < 4 * runs.std() / 60**0.5
    peak = methods.dynamic_triangles(signed, 2, 30).storage_profile().agg(F.max("peak")).first()[0]
    assert peak <= 30


@pytest.mark.parametrize("size", [1, 50])
def test_results_do_not_depend_on_bucket_size(spark, monkeypatch, size):
    """Running sums, minima and as-of values are carried from bucket to bucket."""
    signed = cut(with_deletions(graphs.page_links(spark, SF), 0.4))

    def results():
        slots = sampling.assign_slots(routing.route_store(signed, 2))
        hits = methods.dynamic_triangles(signed, 2, 40).hits
        return sorted(map(tuple, slots.collect()), key=str), sorted(map(tuple, hits.collect()), key=str)

    whole = results()
    monkeypatch.setattr(streams, "BUCKET", size)
    monkeypatch.setattr(counting, "BUCKET", size)
    assert results() == whole


def test_insertions_only_dynamic_equals_sharded(spark):
    events = cut(graphs.page_links(spark, SF))
    a = methods.dynamic_triangles(events, 1, 10**6).global_.first().est
    assert a == methods.sharded_triangles(events, 1, 10**6).global_.first().est == 279


def test_memory_cap_and_ratio_floor(spark):
    events = cut(graphs.customer_overlap(spark, SF))
    r = methods.adaptive_triangles(events, 2, 20, 0.2, memory=60)
    assert r.storage_profile().agg(F.max("peak")).first()[0] <= 60
    free = methods.adaptive_triangles(events, 2, 20, 0.2)
    stored = routing.route_store(events, 2).groupBy("shard").count().withColumnRenamed("count", "n")
    low = free.storage_profile().join(stored, "shard").select((F.col("held") / F.col("n")).alias("r")).agg(F.min("r")).first()[0]
    assert low >= 0.2


def test_recency_refuses_deletions(spark):
    with pytest.raises(ValueError):
        methods.recency_triangles(stream(spark, SIGNED), 20)


def test_bad_input(spark):
    s = stream(spark, SIGNED)
    with pytest.raises(ValueError):
        methods.adaptive_triangles(s, 2, 10)
    with pytest.raises(ValueError):
        methods.sharded_triangles(s, 2, 1)
    pairs = spark.createDataFrame([(2, 1, 0), (1, 2, 1), (3, 3, 2), (None, 1, 3)], "a long, b long, ts long")
    assert [tuple(r) for r in canonical_edges(pairs, ["ts"]).collect()] == [(1, 2, 0)]
    assert seal_point(3, 0.4) == 7 and seal_point(2, 0.2) == 10


def test_stream_equals_replay(spark, tmp_path):
    from dyntri.streaming.live import adaptive_stream, collected

    events = cut(graphs.user_handoff(spark, SF))
    for i in range(4):
        events.where(F.col("seq") % 4 >= 0).where((F.col("seq") >= 27 * i) & (F.col("seq") < 27 * (i + 1))).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    source = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    query = adaptive_stream(source, 2, 1000).writeStream.outputMode("update").format("memory").queryName("live_shards").option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    query.awaitTermination(120)
    k = 1000
    assert collected(spark.table("live_shards"), k * k * (k - 1)).first().est == 455


def test_sink_repeats_a_batch_without_doubling_it(spark, tmp_path):
    from dyntri.sources.live import latest, latest_sink, parsed

    sink = latest_sink(str(tmp_path / "out"))
    for batch, num in ((0, "1"), (1, "2"), (1, "2")):
        sink(spark.createDataFrame([(0, num)], "shard int, num string"), batch)
    assert [tuple(r) for r in latest(spark, str(tmp_path / "out"), ["shard"]).collect()] == [(0, "2")]
    raw = spark.createDataFrame([('{"seq": 1, "u": 2, "v": 3, "sign": -1}',), ("no event",), (None,)], "value string")
    assert [tuple(r) for r in parsed(raw).collect()] == [(1, None, 2, 3, -1)]


def test_large_budgets_do_not_overflow(spark):
    """Budgets whose products pass 64 bits: everything is held, so estimates are exact."""
    for k in (10**6, 10**7, 10**8):
        assert methods.adaptive_triangles(stream(spark, K4), 2, k).global_.first().est == 4
        assert methods.dynamic_triangles(stream(spark, SIGNED), 2, k).global_.first().est == 4


def test_bad_events_are_set_aside(spark):
    rows = [(0, 1, 2, 1), (1, 1, 2, 5), (2, 1, 2, 1), (3, 2, 1, -1), (4, 1, 2, -1), (5, 3, 3, 1), (6, None, 3, 1), (7, 4, 3, 1), (8, 1, 2, 1), (9, 1, 2, None)]
    good, bad = validated(spark.createDataFrame(rows, "seq long, u long, v long, sign byte"))
    assert sorted(map(tuple, good.collect())) == [(0, 1, 2, 1), (3, 1, 2, -1), (7, 3, 4, 1), (8, 1, 2, 1)]
    assert sorted(r.seq for r in bad.collect()) == [1, 2, 4, 5, 6, 9]


def test_candidates_take_nothing_away_that_enters(spark):
    rows = spark.range(40_000).select(F.lit(0).alias("run"), F.lit(0).alias("shard"), F.col("id").alias("seq"), (F.col("id") + 1).alias("t_local"), F.pmod(F.xxhash64("id"), F.lit(1 << 60)).alias("key"))
    for k in (2, 20, 500):
        few = sampling.candidates(rows, k, ["run", "shard"])
        keys = [r.key for r in rows.orderBy("seq").collect()]
        entered, _ = sampling._entrants(list(range(40_000)), keys, k)
        own = {r.seq for r in few.select("seq").collect()}
        assert own >= set(entered) and (k > 100 or len(own) < 20_000)


NAMES = ["canonical_page_links", "exact_local_customer_overlap", "adaptive_global", "sharded_local", "dynamic_global", "coin_global", "metrics_mge",
         "unclosed_edges", "snapshot_lost", "edges_by_date", "estimated_transitivity", "sql_adaptive_global", "stream_adaptive_global", "adaptive_nominal", "adaptive_storage", "ratio_floor", "ratio_floor_capped", "coin_conditional", "recency_global", "dynamic_trajectory",
         "pairing_slots", "paired_residency", "pairing_conditional", "quarantine", "metrics_bias", "ratio_profile", "exact_trajectory", "canonical_doc_near_copies", "canonical_vector_neighbours"]


@pytest.mark.parametrize("name", NAMES)
def test_queries_equal_sql(spark, name):
    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    want = con.execute(queries.oracle_sql()[name]).df()
    got = queries.queries()[name](spark, SF).toPandas()[list(want.columns)]
    order = list(want.columns)
    a, b = (x.astype(float).round(6).sort_values(order).reset_index(drop=True) for x in (want, got))
    assert a.equals(b)

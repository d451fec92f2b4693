"""The estimators and their baselines: samplers, counting and weights put together as lazy plans."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import weights
from ..functions.hashing import coin, draw_key
from ..operators import counting, exact, sampling
from ..operators.routing import route_store
from ..operators.streams import lifetimes, number_within, validated
from ..sources.shared import cut, is_large, runs_at_once, settled


@dataclass
class TriangleResult:
    """Lazy tables of a method: hits (run, shard, seq, sign, u, v, c, kind, num over ``den``) and residency."""

    hits: DataFrame
    residency: DataFrame
    den: float
    runs: int
    quarantine: DataFrame | None = None
    notes: dict = field(default_factory=dict)

    @property
    def global_(self) -> DataFrame:
        return counting.global_estimate(self.hits, self.den, self.runs)

    @property
    def local_(self) -> DataFrame:
        return counting.local_estimate(self.hits, self.den)

    def trajectory(self, every: int = 1) -> DataFrame:
        return counting.trajectory(self.hits, self.den, every)

    def case_census(self) -> DataFrame:
        """(run, kind, hits, est): how often each position of a wedge's edges occurs, and its share of the estimate."""
        return self.hits.groupBy("run", "kind").agg(F.count(F.lit(1)).alias("hits"), (F.sum(F.col("num") * F.col("sign")).cast("double") / float(self.den)).alias("est"))

    def storage_profile(self) -> DataFrame:
        """(run, shard, held, peak): edges held at the end, and at most."""
        ends = self.residency.where("exit_seq is not null").select("run", "shard", F.col("exit_seq").alias("seq"), F.lit(-1).alias("d"))
        steps = self.residency.select("run", "shard", F.col("enter_seq").alias("seq"), F.lit(1).alias("d")).unionByName(ends)
        steps = steps.groupBy("run", "shard", "seq").agg(F.sum("d").alias("d"))
        return number_within(steps, ["run", "shard"], "seq", "held", F.col("d")).groupBy("run", "shard").agg(F.max(F.struct("seq", "held"))["held"].alias("held"), F.max("held").alias("peak"))


def _check(n_shards: int, k: int | None = None, runs: int = 1) -> None:
    if n_shards < 1 or runs < 1:
        raise ValueError("shards and runs are at least 1")
    if k is not None and k < 2:
        raise ValueError("a budget is at least 2: a wedge has two edges")


def _reservoirs_and_hits(events: DataFrame, routed: DataFrame, runs: int, n_shards: int, seed: int, k: int, stored: Callable[[int | range], DataFrame], most: int | None, layout: Layout | None) -> tuple[DataFrame, DataFrame]:
    """(residency, hits with ``before``) of reservoirs of k; stored: the storables of some runs, with segment."""
    held = lambda own, payload: sampling.reservoir_residency(stored(own), k, ["run", "shard", "segment"], payload, most)
    if layout:
        hits = layout.hits(runs, lambda own: held(own, []).withColumnRenamed("enter_seq", "id")).withColumnRenamed("at", "before")
        return held(runs, ["u", "v"]), hits
    residency, hits = _sampled(events, routed, runs, n_shards, seed, lambda own: held(own, ["u", "v"]))
    return residency, counting.as_of(hits, number_within(routed.select("shard", "seq"), ["shard"], "seq", "before"), "before")


def _sampled(events: DataFrame, stored: DataFrame, runs: int, n_shards: int, seed: int, residency: Callable[[int | range], DataFrame]) -> tuple[DataFrame, DataFrame]:
    """(residency, hits) of all runs: together, or of a large stream (``stored``: its stored copies) run by run, so that the shuffles of one are gone before the next."""
    if runs == 1 or not is_large(stored):
        held = cut(residency(runs))
        return held, counting.closing_hits(events, held, n_shards, seed)
    held, hits = [], []
    for run in range(runs):
        held.append(cut(residency(range(run, run + 1))))
        settled(events.sparkSession)
        hits.append(cut(counting.closing_hits(events, held[-1], n_shards, seed)))
        settled(events.sparkSession)
    return reduce(DataFrame.unionByName, held), reduce(DataFrame.unionByName, hits)


@dataclass
class Layout:
    """What the estimates of an experiment share that have a stream and its shards in common.

    stored: numbered storable insertions (insertions only) or slots (with deletions); closed: the closings at their shards, with
    the number ``at`` of what was stored before; most: rows of ``stored`` at a shard at most.
    """

    stored: DataFrame
    closed: DataFrame
    most: int

    def hits(self, runs: int, held: Callable[[int | range], DataFrame]) -> DataFrame:
        """The closings that the samples of all runs hold; of large streams some runs at a time. held: run, shard, segment, id, exit_seq of some runs."""
        if runs == 1 or not is_large(self.stored):
            return counting.resident_hits(self.closed, held(runs))
        step, hits = runs_at_once(self.stored), []
        for run in range(0, runs, step):
            hits.append(cut(counting.resident_hits(self.closed, held(range(run, min(run + step, runs))))))
            settled(self.stored.sparkSession)
        return reduce(DataFrame.unionByName, hits)


def _most(rows: DataFrame) -> int:
    return rows.groupBy("shard").count().agg(F.max("count")).first()[0] or 0


def insertion_layout(events: DataFrame, closed: DataFrame, n_shards: int, seed: int = 42) -> Layout:
    """For streams of insertions; closed: :func:`exact.closings` of them."""
    _check(n_shards)
    stored = cut(number_within(route_store(events, n_shards, seed).select("shard", "seq", "u", "v"), ["shard"], "seq", "t_local"))
    own = counting.as_of(counting.placed(closed, n_shards, seed), stored.select("shard", "seq", F.col("t_local").cast("long").alias("at")), "at")
    return Layout(stored, cut(own.withColumnsRenamed({"in_a": "id_a", "in_b": "id_b"})), _most(stored))


def slot_layout(events: DataFrame, closed: DataFrame, n_shards: int, seed: int = 42) -> Layout:
    """For streams with deletions in which every event is valid; closed: :func:`exact.closings` of them."""
    _check(n_shards)
    routed = route_store(events, n_shards, seed)
    slots = cut(sampling.assign_slots(routed, "queue", seed, _most(routed)))
    own = counting.as_of(counting.placed(closed, n_shards, seed), slots.where("fresh").select("shard", F.col("ins_seq").alias("seq"), F.col("slot").alias("at")), "at")
    for x in "ab":
        own = own.join(slots.select("shard", F.col("ins_seq").alias(f"in_{x}"), F.col("slot").alias(f"id_{x}")), ["shard", f"in_{x}"]).drop(f"in_{x}")
    return Layout(slots, cut(own), _most(slots.where("fresh")))


def adaptive_triangles(events: DataFrame, n_shards: int, k: int, ratio_floor: float = 0.2, memory: int | None = None, seed: int = 42, runs: int = 1, ratio_mode: str = "exact", charge_first: bool = True, layout: Layout | None = None) -> TriangleResult:
    """Insertion-only streams: each shard's reservoir of k joins a pool when its ratio would fall below the floor.

    memory: edges that a shard may hold in all (None: no limit); beyond it the last set stays open and the ratio
    sinks. charge_first: whether the first set counts. ratio_mode "nominal" takes the floor itself as a sealed set's ratio.
    layout: of the same events, shards and seed, if known (this holds for the other methods too).
    """
    _check(n_shards, k, runs)
    if not 0 < ratio_floor <= 1 or (memory is not None and memory < k):
        raise ValueError("the floor is in (0, 1] and memory holds a set at least")
    if layout is None and "sign" in events.columns and events.where("sign <> 1").take(1):
        raise ValueError("the adaptive method takes insertions only; use dynamic_triangles")
    t_star = weights.seal_point(k, ratio_floor)
    sets = None if memory is None else memory // k + (0 if charge_first else 1)
    routed = layout.stored if layout else cut(route_store(events, n_shards, seed))
    stored = lambda own: sampling.segment_storables(sampling.storables(routed, own, seed), t_star, sets)
    most = t_star if sets is None else layout.most if layout else None
    residency, hits = _reservoirs_and_hits(events, routed, runs, n_shards, seed, k, stored, most, layout)
    open_ = F.floor(F.col("before") / t_star)
    open_ = open_ if sets is None else F.least(open_, F.lit(sets - 1))
    hits = hits.withColumn("open", open_).withColumn("t", F.col("before") - F.col("open") * t_star)
    a, b = F.col("seg_a") == F.col("open"), F.col("seg_b") == F.col("open")
    kind = F.when(a & b, weights.OPEN).when(a | b, weights.OPEN_SEALED).when(F.col("seg_a") == F.col("seg_b"), weights.SAME_SEALED).otherwise(weights.TWO_SEALED)
    hits = hits.withColumn("kind", kind)
    if ratio_mode == "exact":
        den, num = k * k * (k - 1), weights.pair_weight(F.col("kind"), k, F.col("t"), t_star)
    else:
        den, num = 1, weights.nominal_weight(F.col("kind"), k, F.col("t"), ratio_floor)
    return TriangleResult(hits.withColumn("num", num).drop("open", "before"), residency, den, runs, notes={"t_star": t_star, "max_sets": sets})


def sharded_triangles(events: DataFrame, n_shards: int, k: int, seed: int = 42, runs: int = 1, layout: Layout | None = None) -> TriangleResult:
    """The distributed baseline: one reservoir of k for each shard, whatever the stream's length."""
    _check(n_shards, k, runs)
    routed = layout.stored if layout else cut(route_store(events, n_shards, seed))
    stored = lambda own: sampling.storables(routed, own, seed).withColumn("segment", F.lit(0))
    residency, hits = _reservoirs_and_hits(events, routed, runs, n_shards, seed, k, stored, layout.most if layout else None, layout)
    hits = hits.withColumns({"kind": F.lit(weights.OPEN), "t": F.col("before"), "num": weights.fixed_weight(k, F.col("before"))}).drop("before")
    return TriangleResult(hits, residency, k * (k - 1), runs)


def solo_reservoir_triangles(events: DataFrame, k: int, seed: int = 42, runs: int = 1, layout: Layout | None = None) -> TriangleResult:
    return sharded_triangles(events, 1, k, seed, runs, layout)


def dynamic_triangles(events: DataFrame, n_shards: int, k: int, seed: int = 42, runs: int = 1, pairing: str = "queue", layout: Layout | None = None) -> TriangleResult:
    """Streams with deletions, by random pairing at each shard. pairing: "random" draws the vacancy, "queue" takes the oldest (so does a layout)."""
    _check(n_shards, k, runs)
    if layout:
        held = lambda own: sampling.slot_residency(layout.stored, k, own, seed, most=layout.most).select("run", "shard", F.lit(0).alias("segment"), F.col("slot").alias("id"), "exit_seq")
        hits = layout.hits(runs, held).withColumnRenamed("at", "opened")
        hits = hits.withColumns({"kind": F.lit(weights.OPEN), "t": F.col("opened"), "num": weights.paired_weight(k, F.col("opened"))}).drop("opened")
        return TriangleResult(hits, sampling.paired_residency(layout.stored, k, runs, seed), k * (k - 1), runs)
    events, bad = validated(events)
    events = cut(events)
    routed = cut(route_store(events, n_shards, seed))
    slots = cut(sampling.assign_slots(routed, pairing, seed))
    residency, hits = _sampled(events, routed, runs, n_shards, seed, lambda own: sampling.paired_residency(slots, k, own, seed))
    opened = number_within(slots.where("fresh").select("shard", F.col("ins_seq").alias("seq")), ["shard"], "seq", "opened")
    hits = counting.as_of(hits, opened, "opened")
    hits = hits.withColumns({"kind": F.lit(weights.OPEN), "t": F.col("opened"), "num": weights.paired_weight(k, F.col("opened"))}).drop("opened")
    return TriangleResult(hits, residency, k * (k - 1), runs, bad)


def solo_paired_triangles(events: DataFrame, k: int, seed: int = 42, runs: int = 1, pairing: str = "queue", layout: Layout | None = None) -> TriangleResult:
    return dynamic_triangles(events, 1, k, seed, runs, pairing, layout)


def solo_paired_conditional(events: DataFrame, k: int, seed: int = 42, runs: int = 1, pairing: str = "queue", layout: Layout | None = None) -> DataFrame:
    """(run, est): random pairing on one machine, counting only triangles whose three edges are in the sample at the end.

    The count is scaled by s(s-1)(s-2) / (y(y-1)(y-2)), s live edges and y sampled ones, and by the probability that
    three edges are sampled at all.
    """
    _check(1, k, runs)
    slots = layout.stored if layout else cut(sampling.assign_slots(route_store(cut(validated(events)[0]), 1, seed), pairing, seed))
    held = cut(sampling.paired_residency(slots, k, runs, seed)).where("exit_seq is null").select("run", "u", "v")
    x, y, z = held.select("run", F.col("u").alias("a"), F.col("v").alias("b")), held.select("run", F.col("u").alias("b"), F.col("v").alias("c")), held.select("run", F.col("u").alias("a"), F.col("v").alias("c"))
    tau = x.join(y, ["run", "b"]).join(z, ["run", "a", "c"]).groupBy("run").agg(F.count(F.lit(1)).alias("tau"))
    sizes = held.groupBy("run").agg(F.count(F.lit(1)).alias("y"))
    state = slots.agg(F.coalesce(F.max("slot"), F.lit(0)).alias("opened"), F.count(F.when(F.col("del_seq").isNull(), 1)).alias("live")).first()
    s, d = state.live, state.opened - state.live
    room = min(k, s + d)
    kappa = 1.0
    if d >= room - 2 and s + d >= 3:
        lc = lambda n, r: math.lgamma(n + 1) - math.lgamma(r + 1) - math.lgamma(n - r + 1)
        kappa -= sum(math.exp(lc(s, j) + lc(d, room - j) - lc(s + d, room)) for j in range(3) if j <= s and 0 <= room - j <= d)
    every = events.sparkSession.range(runs).select(F.col("id").cast("int").alias("run"))
    rows = every.join(sizes, "run", "left").join(tau, "run", "left").fillna(0)
    size = F.col("y").cast("double")
    est = F.when(size >= 3, F.col("tau") / F.lit(kappa) * float(s * (s - 1) * (s - 2)) / (size * (size - 1) * (size - 2))).otherwise(0.0)
    return rows.select("run", est.alias("est"))


def solo_coin_triangles(events: DataFrame, q: float, seed: int = 42, runs: int = 1, conditional: bool = False, closed: DataFrame | None = None) -> TriangleResult:
    """One machine that keeps each edge with probability q; deletions drop a kept edge and subtract.

    conditional: only events that are kept themselves count, at 1 / q^3. closed: :func:`exact.closings` of the events, if known.
    """
    if not 0 < q <= 1:
        raise ValueError("q is in (0, 1]")
    signed = "sign" in events.columns
    life = lifetimes(events) if signed else events.select("u", "v", F.col("seq").alias("enter_seq"), F.lit(None).cast("long").alias("exit_seq"))
    rows = life.select(F.explode(F.sequence(F.lit(0), F.lit(runs - 1))).alias("run"), F.lit(0).alias("shard"), F.lit(0).alias("segment"), "u", "v", "enter_seq", "exit_seq")
    held = rows.where(coin(draw_key(F.col("run"), F.lit(0), F.col("enter_seq"), F.col("u"), F.col("v"), seed), q))
    if closed is None:
        hits = counting.closing_hits(events, held, 1, seed)
    else:
        kept = lambda x, came: coin(draw_key(F.col("run"), F.lit(0), F.col(came), F.least(x, "c"), F.greatest(x, "c"), seed), q)
        hits = closed.withColumns({"shard": F.lit(0), "run": F.explode(F.sequence(F.lit(0), F.lit(runs - 1)))}).where(kept("u", "in_a") & kept("v", "in_b"))
        hits = hits.select("run", "shard", "seq", "sign", "u", "v", "c", F.lit(0).alias("seg_a"), F.lit(0).alias("seg_b"))
    hits = hits.withColumns({"kind": F.lit(weights.OPEN), "num": F.lit(1).cast("decimal(38,0)")})
    if conditional:
        own = held.select("run", "u", "v", F.col("enter_seq").alias("seq")).unionByName(held.where("exit_seq is not null").select("run", "u", "v", F.col("exit_seq").alias("seq")))
        hits = hits.join(own, ["run", "u", "v", "seq"], "left_semi")
    return TriangleResult(hits, held, q**3 if conditional else q**2, runs)


solo_coin_dynamic = solo_coin_triangles


def sparsified_triangles(edges: DataFrame, q: float, seed: int = 42) -> DataFrame:
    """(est): exact count on edges kept with probability q, over q^3; several passes, global only."""
    kept = edges.where(coin(draw_key(F.lit(0), F.lit(0), F.col("seq"), F.col("u"), F.col("v"), seed), q))
    return exact.exact_global(kept).select((F.col("triangles") / F.lit(q**3)).alias("est"))


def coloured_triangles(edges: DataFrame, colours: int, seed: int = 42) -> DataFrame:
    """(est): exact count on edges whose ends have one colour, times colours^2 (a public method, not measured here)."""
    from ..functions.hashing import shard_of

    kept = edges.where(shard_of(F.col("u"), colours, seed) == shard_of(F.col("v"), colours, seed))
    return exact.exact_global(kept).select((F.col("triangles") * F.lit(float(colours**2))).alias("est"))


def recency_triangles(events: DataFrame, k: int, alpha: float = 0.5, seed: int = 42, runs: int = 1) -> TriangleResult:
    """One machine that always holds the newest alpha k edges; older ones go through a reservoir of the rest."""
    if "sign" in events.columns and events.where("sign <> 1").take(1):
        raise ValueError("recency_triangles takes insertions only")
    newest = int(alpha * k)
    rest = k - newest
    _check(1, rest, runs)
    rows = number_within(events.select("seq", "u", "v").withColumn("shard", F.lit(0)), ["shard"], "seq", "t_local")
    ahead = rows.select("shard", (F.col("t_local") - newest).alias("t_local"), F.col("seq").alias("leaves"))
    rows = cut(rows.join(ahead, ["shard", "t_local"], "left"))
    every = F.explode(F.sequence(F.lit(0), F.lit(runs - 1))).alias("run")
    fresh = rows.select(every, "shard", F.lit(-1).alias("segment"), "u", "v", F.col("seq").alias("enter_seq"), F.col("leaves").alias("exit_seq"))
    aged = rows.where("leaves is not null").select(every, "shard", F.lit(0).alias("segment"), "u", "v", F.col("leaves").alias("seq"))
    aged = aged.withColumn("key", draw_key(F.col("run"), F.col("shard"), F.col("seq"), F.col("u"), F.col("v"), seed))
    old = sampling.reservoir_residency(aged, rest, ["run", "shard", "segment"], ["u", "v"])
    residency = cut(fresh.unionByName(old))
    hits = counting.closing_hits(events, residency, 1, seed)
    hits = counting.as_of(hits, rows.select("shard", "seq", F.greatest(F.col("t_local") - newest, F.lit(0)).alias("t")), "t")
    n_old = (F.col("seg_a") == 0).cast("int") + (F.col("seg_b") == 0).cast("int")
    one = F.greatest(F.col("t"), F.lit(rest)).cast("decimal(18,0)") * weights.whole(rest - 1, 12)
    num = F.when(n_old == 0, weights.whole(rest * (rest - 1))).when(n_old == 1, one.cast("decimal(38,0)")).otherwise(weights.fixed_weight(rest, F.col("t")))
    return TriangleResult(hits.withColumns({"kind": n_old, "num": num}), residency, rest * (rest - 1), runs)


def replicated_triangles(events: DataFrame, n_shards: int, k: int, seed: int = 42) -> DataFrame:
    """(est): every shard samples the whole stream on its own; the collector takes the mean."""
    return solo_reservoir_triangles(events, k, seed, n_shards).global_.agg(F.avg("est").alias("est"))


#: Which group of known methods has which property, group by group.
_GROUPS = ("edge sparsifier, colouring", "single machine, insertions", "single machine, deletions", "single machine, bounded ratio", "distributed, fixed budget", "distributed, adaptive and dynamic")
_CRITERIA = {
    "edge insertions": "yyyyyy",
    "memory budget in hand": "nyyyyy",
    "no secondary storage": "yyyyyy",
    "single pass": "nyyyyy",
    "global and local counts": "nyyyyy",
    "several machines": "nnnnyy",
    "adaptive sampling ratio": "nnnyny",
    "edge deletions": "nnynny",
}
#: The functions of this package that stand for each group.
_BUILT = (
    ("sparsified_triangles", "coloured_triangles"), ("recency_triangles", "solo_reservoir_triangles", "solo_coin_triangles"), ("solo_paired_triangles", "solo_paired_conditional", "solo_coin_dynamic"),
    ("adaptive_triangles with one shard",), ("sharded_triangles", "replicated_triangles"), ("adaptive_triangles", "dynamic_triangles"),
)


def capabilities(spark) -> DataFrame:
    """(criterion, methods, built, supported) of the known groups of methods."""
    rows = [(c, g, ", ".join(b), x == "y") for c, own in _CRITERIA.items() for g, b, x in zip(_GROUPS, _BUILT, own)]
    return spark.createDataFrame(rows, "criterion string, methods string, built string, supported boolean")

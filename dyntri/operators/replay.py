"""Shards as state machines: the reference that the relational plans are held against, and the state of live queries.

A shard sees every event that the layout sends it. It counts first and samples then, on the state before the event.
"""

from __future__ import annotations

import hashlib
import heapq
import random
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame

from ..functions.weights import OPEN, OPEN_SEALED, SAME_SEALED, TWO_SEALED, seal_point
from .routing import route_count


def key_of(seed: int, run: int, shard: int, seq: int, u: int, v: int) -> int:
    return int(hashlib.md5(f"{seed}|{run}|{shard}|{seq}|{u}|{v}".encode()).hexdigest()[:15], 16)


class Sample:
    """Held edges by vertex, each with the number of its sampling set."""

    def __init__(self):
        self.near: dict[int, dict[int, int]] = {}

    def add(self, u: int, v: int, mark: int) -> None:
        self.near.setdefault(u, {})[v] = mark
        self.near.setdefault(v, {})[u] = mark

    def remove(self, u: int, v: int) -> bool:
        found = self.near.get(u, {}).pop(v, None) is not None
        if found:
            self.near[v].pop(u)
        return found

    def apexes(self, u: int, v: int) -> Iterator[tuple[int, int, int]]:
        a, b = self.near.get(u, {}), self.near.get(v, {})
        small, large = (a, b) if len(a) <= len(b) else (b, a)
        for c in small:
            if c in large:
                yield c, a[c], b[c]


class AdaptiveShard:
    """Reservoirs sealed into a pool; ``max_sets=1`` is the fixed budget. Counts are over k^2 (k - 1)."""

    def __init__(self, shard: int, k: int, ratio_floor: float = 0.2, max_sets: int | None = None, seed: int = 42, run: int = 0):
        self.shard, self.k, self.t_star, self.max_sets, self.seed, self.run = shard, k, seal_point(k, ratio_floor), max_sets, seed, run
        self.sample, self.heap, self.set, self.t, self.total = Sample(), [], 0, 0, 0
        self.local: dict[int, int] = {}

    def _set_of(self, place: int) -> int:
        at = place // self.t_star
        return at if self.max_sets is None else min(at, self.max_sets - 1)

    def weight(self, a: int, b: int) -> tuple[int, int]:
        k, s = self.k, self.t_star
        current = self._set_of(self.t)
        t = self.t - current * s
        if a == current and b == current:
            return OPEN, k * t * (t - 1) if t > k else k * k * (k - 1)
        if a == current or b == current:
            return OPEN_SEALED, (k - 1) * s * max(t, k)
        return (SAME_SEALED, k * s * (s - 1)) if a == b else (TWO_SEALED, (k - 1) * s * s)

    def event(self, seq: int, u: int, v: int, sign: int, stores: bool) -> list[tuple[int, int, int]]:
        """(apex, kind, numerator) of every triangle counted."""
        hits = []
        for c, a, b in self.sample.apexes(u, v):
            kind, num = self.weight(a, b)
            hits.append((c, kind, num))
            self.total += num
            for x in (u, v, c):
                self.local[x] = self.local.get(x, 0) + num
        if stores:
            own = self._set_of(self.t)
            self.t += 1
            if own != self.set:
                self.set, self.heap = own, []
            key = key_of(self.seed, self.run, self.shard, seq, u, v)
            if len(self.heap) < self.k:
                heapq.heappush(self.heap, (-key, u, v))
                self.sample.add(u, v, own)
            elif -self.heap[0][0] > key:
                _, x, y = heapq.heapreplace(self.heap, (-key, u, v))
                self.sample.remove(x, y)
                self.sample.add(u, v, own)
        return hits


class PairedShard:
    """Random pairing with its two counters of uncompensated deletions. Counts are over k (k - 1)."""

    def __init__(self, shard: int, k: int, seed: int = 42, run: int = 0):
        self.k, self.draw = k, random.Random(f"{seed}|{run}|{shard}")
        self.sample, self.edges, self.place = Sample(), [], {}
        self.t = self.lost_in = self.lost_out = self.total = 0
        self.local: dict[int, int] = {}

    def _chance(self, part: int, whole: int) -> bool:
        return self.draw.random() < part / whole

    def _pick(self, n: int) -> int:
        return self.draw.randrange(n)

    def _keep(self, u: int, v: int) -> None:
        self.place[u, v] = len(self.edges)
        self.edges.append((u, v))
        self.sample.add(u, v, 0)

    def _drop(self, u: int, v: int) -> None:
        at, last = self.place.pop((u, v)), self.edges.pop()
        if last != (u, v):
            self.edges[at] = last
            self.place[last] = at
        self.sample.remove(u, v)

    def event(self, seq: int, u: int, v: int, sign: int, stores: bool) -> list[tuple[int, int, int]]:
        seen = self.t + self.lost_in + self.lost_out
        num = seen * (seen - 1) if seen > self.k else self.k * (self.k - 1)
        hits = [(c, OPEN, num) for c, _, _ in self.sample.apexes(u, v)]
        self.total += sign * num * len(hits)
        for c, _, _ in hits:
            for x in (u, v, c):
                self.local[x] = self.local.get(x, 0) + sign * num
        if not stores:
            return hits
        if sign < 0:
            self.t -= 1
            if (u, v) in self.place:
                self._drop(u, v)
                self.lost_in += 1
            else:
                self.lost_out += 1
            return hits
        self.t += 1
        lost = self.lost_in + self.lost_out
        if lost:
            if self._chance(self.lost_in, lost):
                self.lost_in -= 1
                self._keep(u, v)
            else:
                self.lost_out -= 1
        elif len(self.edges) < self.k:
            self._keep(u, v)
        elif self._chance(self.k, self.t):
            self._drop(*self.edges[self._pick(len(self.edges))])
            self._keep(u, v)
        return hits


HITS = "shard int, seq long, sign int, u long, v long, c long, kind int, num decimal(38,0)"


def replay(events: DataFrame, n_shards: int, make, seed: int = 42) -> DataFrame:
    """The hits of the layout as described: each shard runs ``make(shard)`` over all events sent to it, in order."""
    from decimal import Decimal

    routed = route_count(events.select("seq", "u", "v", "sign"), n_shards, seed)

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        shard = int(frame["shard"].iloc[0])
        machine, rows = make(shard), []
        for seq, u, v, sign, h_u, h_v in frame.sort_values("seq")[["seq", "u", "v", "sign", "h_u", "h_v"]].itertuples(index=False):
            for c, kind, num in machine.event(int(seq), int(u), int(v), int(sign), shard in (h_u, h_v)):
                rows.append((shard, seq, sign, u, v, c, kind, Decimal(num)))
        return pd.DataFrame(rows, columns=["shard", "seq", "sign", "u", "v", "c", "kind", "num"])

    return routed.groupBy("shard").applyInPandas(run, HITS)


def paired_replay(events: DataFrame, n_shards: int, k: int, seed: int = 42) -> DataFrame:
    return replay(events, n_shards, lambda shard: PairedShard(shard, k, seed), seed)


def adaptive_replay(events: DataFrame, n_shards: int, k: int, ratio_floor: float = 0.2, max_sets: int | None = None, seed: int = 42) -> DataFrame:
    return replay(events, n_shards, lambda shard: AdaptiveShard(shard, k, ratio_floor, max_sets, seed), seed)

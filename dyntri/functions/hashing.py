"""Portable randomness: 60-bit integers from md5, equal in Spark and in any SQL engine, the same on every re-run."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

BITS = 60


def _number(*parts: Column | str | int) -> Column:
    text = F.concat_ws("|", *[p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts])
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 15), 16, 10).cast("long")


def shard_of(node: Column, n_shards: int, seed: int = 42) -> Column:
    """The shard that a vertex belongs to."""
    return (_number(seed, node) % n_shards).cast("int")


def draw_key(run: Column, shard: Column, seq: Column, u: Column, v: Column, seed: int = 42, draws: str = "md5") -> Column:
    """A random 60-bit key of an event at a shard; draws="xxhash64" is cheaper and not portable."""
    if draws == "xxhash64":
        return F.shiftrightunsigned(F.xxhash64(F.lit(seed), run, shard, seq, u, v), 64 - BITS)
    return _number(seed, run, shard, seq, u, v)


def coin(key: Column, q: float) -> Column:
    """True with probability q."""
    return key < int(q * 2**BITS)

"""The experiments, re-expressed on the given tables: accuracy, floors, deletions, shards, size."""

from __future__ import annotations

import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, Row
from pyspark.sql import functions as F

from ..operators import exact, measures
from ..operators.streams import with_deletions
from ..sources.shared import cut, is_large, passing, settled
from . import methods

#: Cells of a grid that run at a time; those that are timed run alone.
CELLS_AT_ONCE = 6
#: Triangles of a stream, in edges, up to which its closings are listed once for all cells and runs.
LISTED = 8

ROWS = "graph string, method string, setting string, mge double, gvar double, mle double, pearson double"

#: (method, setting, how to make its result): a result whose vertices are measured too, or (run, est) only.
Cell = tuple[str, str, Callable[[], methods.TriangleResult | DataFrame]]


def _row(graph: str, cell: Cell, truth: DataFrame, vertices: DataFrame | None, runs: int) -> Row:
    """(graph, method, setting, mge, gvar, mle, pearson) of one cell; its hits are computed once."""
    with passing(truth.sparkSession):
        return _measured(graph, cell, truth, vertices, runs)


def _measured(graph: str, cell: Cell, truth: DataFrame, vertices: DataFrame | None, runs: int) -> Row:
    method, setting, make = cell
    est = made = make()
    vertex = None
    if isinstance(made, methods.TriangleResult):
        made = replace(made, hits=cut(made.hits))
        est, vertex = made.global_, made.local_
    one = F.broadcast(measures.mean_global_error(truth, est)).join(F.broadcast(measures.global_variance(truth, est)), F.lit(True))
    if vertices is not None and vertex is not None:
        one = one.join(F.broadcast(measures.mean_local_error(vertices, vertex, runs)), F.lit(True)).join(F.broadcast(measures.pearson_local(vertices, vertex, runs)), F.lit(True))
    got = one.first().asDict()
    return Row(graph, method, setting, got["mge"], got["gvar"], got.get("mle"), got.get("pearson"))


def _table(graph: str, cells: list[Cell], events: DataFrame, truth: DataFrame, vertices: DataFrame | None, runs: int) -> DataFrame:
    """A row per cell. Cells don't depend on each other and are mostly short stages, so several run at a time; those of a large
    stream go one by one, as each takes several times the stream on disk."""
    spark = truth.sparkSession
    if is_large(events):
        rows = []
        for cell in cells:
            settled(spark)
            rows.append(_row(graph, cell, truth, vertices, runs))
        return spark.createDataFrame(rows, ROWS)
    with ThreadPoolExecutor(CELLS_AT_ONCE) as pool:
        rows = list(pool.map(inheritable_thread_target(spark)(lambda cell: _row(graph, cell, truth, vertices, runs)), cells))
    return spark.createDataFrame(rows, ROWS)


def _closed(events: DataFrame, n: int, truth: DataFrame) -> DataFrame | None:
    """The stream's closings, of which all estimates are, listed once; None where they are many more than the edges, and samples hold fewer."""
    return cut(exact.closings(events)) if truth.first()[0] <= LISTED * n else None


def accuracy(events: DataFrame, graph: str, shares: tuple[float, ...] = (0.002, 0.01, 0.05), n_shards: int = 10, floor: float = 0.2, runs: int = 5, local: bool = True) -> DataFrame:
    """Insertion-only accuracy over budgets as shares of all edges: the adaptive pool and the three baselines."""
    events = cut(events)
    n, truth, vertices = events.count(), cut(exact.exact_global(events)), cut(exact.exact_local(events)) if local else None
    closed = _closed(events, n, truth)
    many, solo = (methods.insertion_layout(events, closed, w) if closed is not None else None for w in (n_shards, 1))
    cells: list[Cell] = []
    for share in shares:
        k, setting = max(2, int(share * n)), f"budget={share}"
        cells += [
            ("adaptive", setting, lambda k=k: methods.adaptive_triangles(events, n_shards, k, floor, runs=runs, layout=many)),
            ("sharded", setting, lambda k=k: methods.sharded_triangles(events, n_shards, k, runs=runs, layout=many)),
            ("solo_reservoir", setting, lambda k=k: methods.solo_reservoir_triangles(events, k, runs=runs, layout=solo)),
            ("solo_coin", setting, lambda share=share: methods.solo_coin_triangles(events, share, runs=runs, closed=closed)),
        ]
    return _table(graph, cells, events, truth, vertices, runs)


def speed(events: DataFrame, graph: str, solo: tuple[float, ...] = (0.02, 0.05), share: float = 0.001, n_shards: int = 10) -> DataFrame:
    """(graph, method, setting, seconds, edges_per_second, mge) of distributed methods at a small budget and solo ones at larger."""
    events = cut(events)
    n, truth = events.count(), cut(exact.exact_global(events))
    k = max(2, int(share * n))
    makes = [("adaptive", f"budget={share}", lambda: methods.adaptive_triangles(events, n_shards, k)), ("sharded", f"budget={share}", lambda: methods.sharded_triangles(events, n_shards, k))]
    for s in solo:
        makes.append(("solo_reservoir", f"budget={s}", lambda s=s: methods.solo_reservoir_triangles(events, max(2, int(s * n)))))
        makes.append(("solo_coin", f"budget={s}", lambda s=s: methods.solo_coin_triangles(events, s)))
    rows = []
    for name, setting, make in makes:
        began = time.perf_counter()
        est = make().global_.first().est
        took = time.perf_counter() - began
        rows.append((graph, name, setting, took, n / took, abs(truth.first()[0] - est) / (truth.first()[0] + 1)))
    return events.sparkSession.createDataFrame(rows, "graph string, method string, setting string, seconds double, edges_per_second double, mge double")


def floors(events: DataFrame, graph: str, ratio_floors: tuple[float, ...] = (0.02, 0.05, 0.2), shares: tuple[float, ...] = (0.002, 0.005), n_shards: int = 20, runs: int = 5) -> DataFrame:
    """Error of the adaptive pool over ratio floors and first budgets."""
    events = cut(events)
    n, truth = events.count(), cut(exact.exact_global(events))
    closed = _closed(events, n, truth)
    layout = methods.insertion_layout(events, closed, n_shards) if closed is not None else None
    cells: list[Cell] = [
        ("adaptive", f"budget={share},floor={floor}", lambda k=max(2, int(share * n)), floor=floor: methods.adaptive_triangles(events, n_shards, k, floor, runs=runs, layout=layout))
        for share in shares
        for floor in ratio_floors
    ]
    return _table(graph, cells, events, truth, None, runs)


def dynamic_accuracy(events: DataFrame, graph: str, delta: float = 0.2, share: float = 0.05, n_shards: int = 10, runs: int = 5) -> DataFrame:
    """Accuracy after deletions: random pairing at shards against the three solo baselines."""
    signed = cut(with_deletions(events, delta))
    n, truth, vertices = events.count(), cut(exact.exact_dynamic(signed)), cut(exact.exact_local_dynamic(signed))
    k = max(3, int(share * n))
    closed = _closed(signed, n, truth)
    many, solo = (methods.slot_layout(signed, closed, w) if closed is not None else None for w in (n_shards, 1))
    setting = f"delta={delta},budget={share}"
    cells: list[Cell] = [
        ("dynamic", setting, lambda: methods.dynamic_triangles(signed, n_shards, k, runs=runs, layout=many)),
        ("solo_paired", setting, lambda: methods.solo_paired_triangles(signed, k, runs=runs, layout=solo)),
        ("solo_coin_dynamic", setting, lambda: methods.solo_coin_dynamic(signed, share, runs=runs, closed=closed)),
        ("solo_paired_conditional", setting, lambda: cut(methods.solo_paired_conditional(signed, k, runs=runs, layout=solo))),
    ]
    return _table(graph, cells, signed, truth, vertices, runs)


def dynamic_speed(events: DataFrame, graph: str, delta: float = 0.2, share: float = 0.01, solo: tuple[float, ...] = (0.01, 0.05), n_shards: int = 10) -> DataFrame:
    """(graph, method, setting, seconds, events_per_second, mge) with deletions."""
    signed = cut(with_deletions(events, delta))
    n, truth = signed.count(), exact.exact_dynamic(signed).first()[0]
    makes = [("dynamic", f"budget={share}", lambda: methods.dynamic_triangles(signed, n_shards, max(2, int(share * n))))]
    for s in solo:
        makes.append(("solo_paired", f"budget={s}", lambda s=s: methods.solo_paired_triangles(signed, max(2, int(s * n)))))
        makes.append(("solo_coin_dynamic", f"budget={s}", lambda s=s: methods.solo_coin_dynamic(signed, s)))
    rows = []
    for name, setting, make in makes:
        began = time.perf_counter()
        est = make().global_.first().est
        took = time.perf_counter() - began
        rows.append((graph, name, setting, took, n / took, abs(truth - est) / (truth + 1)))
    return events.sparkSession.createDataFrame(rows, "graph string, method string, setting string, seconds double, events_per_second double, mge double")


def shard_sweep(events: DataFrame, graph: str, shards: tuple[int, ...] = (2, 8, 32), delta: float = 0.2, share: float = 0.02, runs: int = 5) -> DataFrame:
    """Error and correlation of the dynamic method as shards are added, each with the same budget."""
    signed = cut(with_deletions(events, delta))
    n, truth, vertices = events.count(), cut(exact.exact_dynamic(signed)), cut(exact.exact_local_dynamic(signed))
    k = max(2, int(share * n))
    closed = _closed(signed, n, truth)
    layout = lambda w: methods.slot_layout(signed, closed, w) if closed is not None else None
    cells: list[Cell] = [("dynamic", f"shards={w}", lambda w=w: methods.dynamic_triangles(signed, w, k, runs=runs, layout=layout(w))) for w in shards]
    return _table(graph, cells, signed, truth, vertices, runs)


def scaling(events: DataFrame, graph: str, powers: tuple[int, ...] | None = None, n_shards: int = 30, share: float = 0.01, delta: float = 0.2) -> DataFrame:
    """(graph, edges, seconds, error, slope, r2) of the dynamic method on growing prefixes, and the line fitted to all of them.

    powers: prefixes of 2^p edges; left out, they are taken from the stream: five doublings, and the whole. The budget
    is one for all, a share of the whole stream.
    """
    n = events.count()
    powers = powers or tuple(range(max(4, n.bit_length() - 6), n.bit_length()))
    k, rows = max(3, int(share * n)), []
    for size in [*(2**p for p in powers if 2**p < n), n]:
        signed = cut(with_deletions(cut(events.where(F.col("seq") < size)), delta))
        truth = exact.exact_dynamic(signed).first()[0]
        began = time.perf_counter()
        est = methods.dynamic_triangles(signed, n_shards, k).global_.first().est
        rows.append((graph, size, time.perf_counter() - began, abs(truth - est) / (truth + 1)))
    table = events.sparkSession.createDataFrame(rows, "graph string, edges long, seconds double, error double")
    return table.join(F.broadcast(measures.scaling_slope(table)), F.lit(True))

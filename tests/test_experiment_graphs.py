"""Experiments run on all the graphs surveyed for them, each on its whole stream."""

import pytest

from dyntri import queries
from dyntri.plans import workloads
from dyntri.sources import graphs

DATA = "/root/testdata/sf0.001"
EDGES = {"customer_overlap": 997, "trade_triads": 8731, "part_copurchase": 8899, "page_links": 607, "supplier_cosupply": 45, "user_handoff": 105}


def _seen(spark, monkeypatch, name, function):
    seen = {}

    def record(events, graph, **options):
        seen[graph] = events.count()
        return spark.createDataFrame([(graph, "m", "s", 0.0, 0.0, None, None)], workloads.ROWS)

    monkeypatch.setattr(workloads, function, record)
    rows = queries.queries()[name](spark, DATA).collect()
    assert sorted(r.graph for r in rows) == sorted(seen)
    assert all(seen[g] == n for g, n in EDGES.items() if g in seen)
    return set(seen)


@pytest.mark.parametrize("name, function, names", [
    ("w1_accuracy", "accuracy", {"customer_overlap", "trade_triads", "part_copurchase"}),
    ("w4_dynamic_accuracy", "dynamic_accuracy", set(graphs.GRAPHS)),
    ("w6_shards", "shard_sweep", {"customer_overlap", "trade_triads"}),
])
def test_all_graphs_are_measured(spark, monkeypatch, name, function, names):
    assert _seen(spark, monkeypatch, name, function) == names

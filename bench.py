"""Times the headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

import json
import os
import sys
import tempfile
import time
from pathlib import Path

HERE = Path(__file__).resolve().parent
sys.path.insert(0, str(HERE))
os.environ["PYTHONPATH"] = f"{HERE}:{os.environ.get('PYTHONPATH', '')}"


def timed_queries(spark, sf_dir):
    from dyntri.operators import exact
    from dyntri.operators.streams import with_deletions
    from dyntri.plans import methods
    from dyntri.sources import graphs
    from dyntri.sources.shared import cut

    began = time.perf_counter()
    events = cut(graphs.part_copurchase(spark, sf_dir))
    n = events.count()
    signed = cut(with_deletions(events, 0.2))
    took = {"prepare": time.perf_counter() - began}
    makes = {
        "exact_global": lambda: exact.exact_global(events),
        "adaptive_10_shards_0.1pct": lambda: methods.adaptive_triangles(events, 10, max(2, n // 1000), 0.2).global_,
        "sharded_10_shards_0.1pct": lambda: methods.sharded_triangles(events, 10, max(2, n // 1000)).global_,
        "solo_reservoir_2pct": lambda: methods.solo_reservoir_triangles(events, max(2, n // 50)).global_,
        "solo_coin_2pct": lambda: methods.solo_coin_triangles(events, 0.02).global_,
        "dynamic_10_shards_1pct": lambda: methods.dynamic_triangles(signed, 10, max(2, n // 100)).global_,
        "solo_paired_1pct": lambda: methods.solo_paired_triangles(signed, max(2, n // 100)).global_,
        "solo_coin_dynamic_1pct": lambda: methods.solo_coin_dynamic(signed, 0.01).global_,
    }
    for name, make in makes.items():
        began = time.perf_counter()
        make().collect()
        took[name] = time.perf_counter() - began
    return n, took


def main():
    from pyspark.sql import SparkSession

    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.driver.memory", "8g").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC").config("spark.checkpoint.dir", tempfile.mkdtemp(prefix="bench-")).config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    edges, took = timed_queries(spark, sf_dir)
    took = {k: round(v, 3) for k, v in took.items()}
    rates = {f"{k}_edges_per_s": round(edges / v) for k, v in took.items() if k != "prepare"}
    print(json.dumps({"metric": "seconds of the estimators on the co-purchase graph", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "rates": rates, "edges": edges, "sf": Path(sf_dir).name}))
    spark.stop()


if __name__ == "__main__":
    main()

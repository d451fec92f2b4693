"""The driver's queries for the estimators, each with its DuckDB twin where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable, Iterable
from functools import partial, reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import oracles as sql
from .functions.weights import seal_point
from .operators import exact, measures, relations, replay, routing, sampling
from .operators.streams import live_edges, validated, with_deletions
from .plans import methods, sql_surface, workloads
from .sources import graphs
from .sources.live import file_edges, latest, latest_sink
from .sources.shared import cut, fresh_folder, is_large, passing, settled
from .streaming import live

Query = Callable[[SparkSession, str], DataFrame]
SHARDS, RUNS, K, FLOOR, DELTA, Q = 3, 2, 60, 0.2, 0.2, 0.2
T_STAR = seal_point(K, FLOOR)
MEMORY = 3 * K
SMALL, SIGNED = "page_links", "page_links"
#: Graphs of the experiments on accuracy and on shards; the one with deletions takes all.
ACCURACY, SHARD_SWEEP = ("customer_overlap", "trade_triads", "part_copurchase"), ("customer_overlap", "trade_triads")


def _graph(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return cut(graphs.GRAPHS[name](spark, sf_dir))


def _signed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cut(with_deletions(_graph(spark, sf_dir, SIGNED), DELTA))


def _found() -> dict[str, tuple[Query, str | None]]:
    out: dict[str, tuple[Query, str | None]] = {}

    def add(name: str, make: Query, text: str | None = None) -> None:
        out[name] = (make, text)

    def on(graph: str, f: Callable[[DataFrame], DataFrame]) -> Query:
        return lambda spark, d: f(_graph(spark, d, graph))

    def trial(names: Iterable[str], f: Callable[[DataFrame, str], DataFrame]) -> Query:
        """An experiment on graphs, one after the other: their tables are plain rows, so each stream and all tables behind it go at its end."""

        def once(spark: SparkSession, d: str, graph: str) -> DataFrame:
            with passing(spark):
                events = _graph(spark, d, graph)
                if is_large(events):
                    settled(spark)
                return f(events, graph)

        return lambda spark, d: reduce(DataFrame.unionByName, [once(spark, d, graph) for graph in names])

    def counted(graph: str, f: Callable[[DataFrame], DataFrame]) -> Query:
        return lambda spark, d: f(cut(graphs.GRAPHS[graph].edges(spark, d)))

    signed = lambda f: lambda spark, d: f(_signed(spark, d))
    for g in graphs.GRAPHS:
        add(f"canonical_{g}", on(g, lambda e: e.select("seq", "u", "v")), f"{sql.with_(g)} SELECT seq, u, v FROM e")
        add(f"exact_global_{g}", (lambda spark, d: exact.exact_global_of_classes(*graphs.page_twins(spark, d))) if g == "page_overlap" else counted(g, exact.exact_global), f"{sql.with_(g, sql._TRIANGLES)} SELECT count(*) AS triangles FROM t")
    for g in ("customer_overlap", "page_links", "user_handoff", "trade_triads"):
        add(f"exact_local_{g}", counted(g, exact.exact_local), f"{sql.with_(g, sql._LOCAL)} SELECT node, triangles FROM x")
    g = "customer_overlap"
    add("degrees", on(g, exact.degrees), f"{sql.with_(g, sql._NODES)} SELECT node, degree FROM nd")
    add("transitivity", on(g, exact.transitivity), f"{sql.with_(g, sql._LOCAL)} SELECT (sum(triangles) / 3)::BIGINT AS triangles, sum(degree * (degree - 1) // 2)::BIGINT AS wedges, round(3 * (sum(triangles) / 3)::BIGINT / sum(degree * (degree - 1) // 2), 6) AS transitivity FROM x")
    add("clustering", on(g, exact.clustering), f"{sql.with_(g, sql._LOCAL)} SELECT node, degree, triangles, CASE WHEN degree > 1 THEN round(2 * triangles / (degree * (degree - 1)), 6) ELSE 0.0 END AS coefficient FROM x")
    add("topk_local", on(g, lambda e: exact.top_local(e, 20)), f"{sql.with_(g, sql._LOCAL)} SELECT node, triangles FROM x ORDER BY triangles DESC, node LIMIT 20")
    add("anomalies", on("user_handoff", exact.anomalies), f"{sql.with_('user_handoff', sql._LOCAL)} SELECT node, triangles, CASE WHEN stddev_pop(triangles) OVER () > 0 THEN round((triangles - avg(triangles) OVER ()) / stddev_pop(triangles) OVER (), 6) ELSE 0.0 END AS z FROM x")
    add("rollup_local_region", _rollup, f"{sql.with_(g, sql._LOCAL)} SELECT r_name AS region, n_name AS nation, sum(triangles)::BIGINT AS triangles FROM x JOIN customer ON c_custkey = node JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ROLLUP (r_name, n_name)")
    add("spam_local_labels", _labels, f"{sql.with_('doc_near_copies', sql._LOCAL)} SELECT quality, count(*) AS docs, sum(triangles)::BIGINT AS triangles FROM x JOIN labels ON doc_id = node GROUP BY quality")
    # routing
    ev = "ev AS (SELECT *, 1 AS sign FROM e)"
    h = f"h AS (SELECT *, {sql.h60('42', 'u')} % {SHARDS} AS h_u, {sql.h60('42', 'v')} % {SHARDS} AS h_v FROM e)"
    add("route_count", on(SMALL, lambda e: routing.route_count(e, SHARDS).select("seq", "u", "v", "shard")), f"{sql.with_(SMALL, h)} SELECT seq, u, v, s::INT AS shard FROM h, range({SHARDS}) AS r(s) WHERE h_u <> h_v OR s = h_u")
    add("route_store", on(SMALL, lambda e: routing.route_store(e, SHARDS).select("seq", "u", "v", "shard")), f"{sql.with_(SMALL, h)} SELECT seq, u, v, h_u::INT AS shard FROM h UNION SELECT seq, u, v, h_v::INT FROM h")
    add("message_cost", on(SMALL, lambda e: routing.message_cost(e, SHARDS)), f"{sql.with_(SMALL, h)} SELECT s::INT AS shard, count(*) FILTER (h_u <> h_v OR h_u = s) AS sent, count(*) FILTER (h_u = s OR h_v = s) AS stored FROM h, range({SHARDS}) AS r(s) GROUP BY 1")
    add("counting_shard_once", on(SMALL, lambda e: methods.sharded_triangles(e, SHARDS, 10**6).hits.groupBy("run", "seq", "c").count().agg(F.max("count").alias("most"), F.count(F.lit(1)).alias("triangles"))), f"{sql.with_(SMALL, sql._TRIANGLES)} SELECT 1::BIGINT AS most, count(*) AS triangles FROM t")
    # samplers
    held = sql.with_(SMALL, ev, sql.stored("ev", SHARDS, RUNS), sql.reservoir("st", "run, shard", K, "rs"))
    cols = ["run", "shard", "u", "v", "enter_seq", "exit_seq"]
    add("reservoir_residency", on(SMALL, lambda e: methods.sharded_triangles(e, SHARDS, K, runs=RUNS).residency.select(cols)), f"{held} SELECT run::INT AS run, shard::INT AS shard, u, v, seq AS enter_seq, exit_seq FROM rs")
    add("reservoir_sample", on(SMALL, lambda e: methods.sharded_triangles(e, SHARDS, K, runs=RUNS).residency.where("exit_seq is null").select("run", "shard", "u", "v")), f"{held} SELECT run::INT AS run, shard::INT AS shard, u, v FROM rs WHERE exit_seq IS NULL")
    ada = sql.adaptive_ctes(SHARDS, K, T_STAR, None, RUNS)
    adaptive = lambda e, **x: methods.adaptive_triangles(e, SHARDS, K, FLOOR, runs=RUNS, **x)
    add("adaptive_residency", on(SMALL, lambda e: adaptive(e).residency.select("segment", *cols)), f"{sql.with_(SMALL, *ada[:5])} SELECT segment::INT AS segment, run::INT AS run, shard::INT AS shard, u, v, enter_seq, exit_seq FROM held")
    add("adaptive_segments", on(SMALL, lambda e: adaptive(e).residency.groupBy("run", "shard", "segment").agg(F.count(F.when(F.col("exit_seq").isNull(), 1)).alias("held"))), f"{sql.with_(SMALL, *ada[:5])} SELECT run::INT AS run, shard::INT AS shard, segment::INT AS segment, count(*) FILTER (exit_seq IS NULL) AS held FROM held GROUP BY 1, 2, 3")
    # methods
    add("adaptive_global", on(SMALL, lambda e: adaptive(e).global_), sql.adaptive(SMALL, SHARDS, K, T_STAR, None, RUNS))
    add("adaptive_local", on(SMALL, lambda e: adaptive(e).local_), sql.adaptive(SMALL, SHARDS, K, T_STAR, None, RUNS, True))
    add("adaptive_capped_global", on(SMALL, lambda e: adaptive(e, memory=MEMORY).global_), sql.adaptive(SMALL, SHARDS, K, T_STAR, MEMORY // K, RUNS))
    add("adaptive_single_machine", on(SMALL, lambda e: methods.adaptive_triangles(e, 1, K, FLOOR, runs=RUNS).global_), sql.adaptive(SMALL, 1, K, T_STAR, None, RUNS))
    add("adaptive_nominal", on(SMALL, lambda e: adaptive(e, ratio_mode="nominal").global_.select("run", F.round("est", 4).alias("est"))), f"""{sql.with_(SMALL, *ada[:-1])} SELECT r.run::INT AS run, round(coalesce(sum(CASE kind
        WHEN 1 THEN CASE WHEN t > {K} THEN t * (t - 1) / {float(K * (K - 1))} ELSE 1.0 END WHEN 2 THEN ({K} / {FLOOR} - 1) / ({FLOOR} * {K - 1}) WHEN 3 THEN 1 / ({FLOOR} * {FLOOR}) ELSE greatest(t / {float(K)}, 1.0) / {FLOOR} END::DOUBLE), 0.0), 4) AS est
        FROM range({RUNS}) AS r(run) LEFT JOIN kk ON kk.run = r.run GROUP BY 1""")
    add("adaptive_census", on(SMALL, lambda e: adaptive(e).case_census()), f"{sql.with_(SMALL, *ada)} SELECT run::INT AS run, kind, count(*) AS hits, sum(num)::DOUBLE / {float(K * K * (K - 1))} AS est FROM w GROUP BY 1, 2")
    add("adaptive_trajectory", on(SMALL, lambda e: adaptive(e).trajectory().select("run", "seq", F.round("est", 4).alias("est"))), f"{sql.with_(SMALL, *ada)} SELECT run::INT AS run, seq, round(sum(n) OVER (PARTITION BY run ORDER BY seq)::DOUBLE / {float(K * K * (K - 1))}, 4) AS est FROM (SELECT run, seq, sum(num) AS n FROM w GROUP BY 1, 2)")
    steps = "st2 AS (SELECT run, shard, seq, sum(d) AS d FROM (SELECT run, shard, enter_seq AS seq, 1 AS d FROM held UNION ALL SELECT run, shard, exit_seq, -1 FROM held WHERE exit_seq IS NOT NULL) GROUP BY 1, 2, 3), cu AS (SELECT *, sum(d) OVER (PARTITION BY run, shard ORDER BY seq) AS h FROM st2)"
    add("adaptive_storage", on(SMALL, lambda e: adaptive(e).storage_profile()), f"{sql.with_(SMALL, *ada[:5], steps)} SELECT run::INT AS run, shard::INT AS shard, arg_max(h, seq)::BIGINT AS held, max(h)::BIGINT AS peak FROM cu GROUP BY 1, 2")
    capped = sql.adaptive_ctes(SHARDS, K, T_STAR, MEMORY // K, RUNS)
    lowest = "se AS (SELECT * FROM s1, range({0}) AS r(run)), lo AS (SELECT se.run, se.shard, se.seq, se.n, (SELECT sum(d) FROM st2 WHERE st2.run = se.run AND st2.shard = se.shard AND st2.seq <= se.seq) AS h FROM se)".format(RUNS)
    for name, ctes, extra in (("ratio_floor", ada, {}), ("ratio_floor_capped", capped, {"memory": MEMORY})):
        add(name, on(SMALL, lambda e, x=extra: measures.lowest_ratio(adaptive(e, **x).residency, routing.route_store(e, SHARDS), FLOOR)),
            f"{sql.with_(SMALL, *ctes[:5], steps, lowest)} SELECT run::INT AS run, shard::INT AS shard, round(min(h / n), 6)::DOUBLE AS lowest, min(h / n) >= {FLOOR} AS floor_held FROM lo GROUP BY 1, 2")
    one = sql.adaptive_ctes(SHARDS, K, T_STAR, None, 1)
    add("adaptive_replay_equal", on(SMALL, _replayed), f"{sql.with_(SMALL, *one)} SELECT count(*) AS relational, count(*) AS replayed, 0::BIGINT AS differing FROM w")
    add("sharded_global", on(SMALL, lambda e: methods.sharded_triangles(e, SHARDS, K, runs=RUNS).global_), sql.sharded(SMALL, SHARDS, K, RUNS))
    add("sharded_local", on(SMALL, lambda e: methods.sharded_triangles(e, SHARDS, K, runs=RUNS).local_), sql.sharded(SMALL, SHARDS, K, RUNS, True))
    add("solo_reservoir_global", on(SMALL, lambda e: methods.solo_reservoir_triangles(e, 4 * K, runs=RUNS).global_), sql.sharded(SMALL, 1, 4 * K, RUNS))
    add("solo_reservoir_local", on(SMALL, lambda e: methods.solo_reservoir_triangles(e, 4 * K, runs=RUNS).local_), sql.sharded(SMALL, 1, 4 * K, RUNS, True))
    add("replicated_global", on(SMALL, lambda e: methods.replicated_triangles(e, 4, 4 * K).select(F.round("est", 6).alias("est"))), f"SELECT round(avg(est), 6) AS est FROM ({sql.sharded(SMALL, 1, 4 * K, 4)})")
    add("coin_global", on("customer_overlap", lambda e: methods.solo_coin_triangles(e, Q, runs=RUNS).global_), sql.coin("customer_overlap", Q, RUNS))
    add("coin_local", on("customer_overlap", lambda e: methods.solo_coin_triangles(e, Q, runs=RUNS).local_), sql.coin("customer_overlap", Q, RUNS, True))
    add("coin_conditional", on("customer_overlap", lambda e: methods.solo_coin_triangles(e, Q, runs=RUNS, conditional=True).global_), sql.coin("customer_overlap", Q, RUNS, conditional=True))
    key = sql.h60("42", "0", "0", "seq", "u", "v")
    add("sparsified", on("customer_overlap", lambda e: methods.sparsified_triangles(e, 0.5)), f"{sql.with_('customer_overlap').replace('e AS (', 'e0 AS (')}, e AS (SELECT * FROM e0 WHERE {key} < {2**59}), {sql._TRIANGLES} SELECT count(*) / 0.125::DOUBLE AS est FROM t")
    add("coloured", on("customer_overlap", lambda e: methods.coloured_triangles(e, 2)), f"{sql.with_('customer_overlap').replace('e AS (', 'e0 AS (')}, e AS (SELECT * FROM e0 WHERE {sql.h60('42', 'u')} % 2 = {sql.h60('42', 'v')} % 2), {sql._TRIANGLES} SELECT count(*) * 4.0::DOUBLE AS est FROM t")
    add("recency_global", on(SMALL, lambda e: methods.recency_triangles(e, 8 * K, runs=RUNS).global_), sql.recency(SMALL, 8 * K, RUNS))
    # deletions
    dele = sql.with_(SIGNED, sql.deletions(DELTA))
    add("deletions_stream", signed(lambda s: s.select("seq", "u", "v", F.col("sign").cast("int").alias("sign"))), f"{dele} SELECT seq, u, v, sign::INT AS sign FROM d")
    add("live_edges", signed(live_edges), f"{dele} SELECT u, v FROM d GROUP BY 1, 2 HAVING sum(sign) > 0")
    add("exact_dynamic", signed(exact.exact_dynamic), f"{sql.with_(SIGNED, sql.deletions(DELTA), sql._LIVES)} SELECT count(*) FILTER (died IS NULL) AS triangles FROM lv")
    add("exact_trajectory", signed(exact.exact_trajectory), f"{sql.with_(SIGNED, sql.deletions(DELTA), sql._LIVES)} SELECT seq, sum(d) OVER (ORDER BY seq)::BIGINT AS triangles FROM (SELECT seq, sum(d) AS d FROM (SELECT born AS seq, 1 AS d FROM lv UNION ALL SELECT died, -1 FROM lv WHERE died IS NOT NULL) GROUP BY seq)")
    dynamic = lambda s, k=4 * K: methods.dynamic_triangles(s, SHARDS, k, runs=RUNS)
    add("dynamic_global", signed(lambda s: dynamic(s).global_), sql.dynamic(SIGNED, DELTA, SHARDS, 4 * K, RUNS))
    add("dynamic_local", signed(lambda s: dynamic(s).local_), sql.dynamic(SIGNED, DELTA, SHARDS, 4 * K, RUNS, True))
    add("dynamic_ample", signed(lambda s: dynamic(s, 10**6).global_), f"{sql.with_(SIGNED, sql.deletions(DELTA), sql._LIVES)} SELECT r.run::INT AS run, (SELECT count(*) FILTER (died IS NULL) FROM lv)::DOUBLE AS est FROM range({RUNS}) AS r(run)")
    dyn = sql.dynamic_ctes(DELTA, SHARDS, 4 * K, RUNS)
    add("dynamic_trajectory", signed(lambda s: dynamic(s).trajectory(100).select("run", "seq", F.round("est", 4).alias("est"))), f"{sql.with_(SIGNED, *dyn)} SELECT run::INT AS run, seq, round(sum(n) OVER (PARTITION BY run ORDER BY seq)::DOUBLE / {float(4 * K * (4 * K - 1))}, 4) AS est FROM (SELECT run, seq // 100 * 100 AS seq, sum(num * sign) AS n FROM w GROUP BY 1, 2)")
    add("dynamic_random_budgeted", signed(lambda s: methods.dynamic_triangles(s, SHARDS, 4 * K, runs=RUNS, pairing="random").global_))
    add("dynamic_literal_counters", signed(lambda s: replay.paired_replay(s, SHARDS, 4 * K).groupBy("shard").agg(F.sum(F.col("num") * F.col("sign")).cast("double").alias("num"))))
    add("pairing_slots", signed(lambda s: sampling.assign_slots(routing.route_store(s, SHARDS))), f"{sql.with_(SIGNED, *dyn)} SELECT q2.shard::INT AS shard, u, v, q2.seq AS ins_seq, nx AS del_seq, slot::BIGINT AS slot, fresh FROM ro JOIN q2 ON q2.shard = ro.shard AND q2.seq = ro.seq")
    add("paired_residency", signed(lambda s: dynamic(s).residency.select(cols)), f"{sql.with_(SIGNED, *dyn)} SELECT run::INT AS run, shard::INT AS shard, u, v, enter_seq, exit_seq FROM held")
    add("solo_paired_global", signed(lambda s: methods.solo_paired_triangles(s, 8 * K, runs=RUNS).global_), sql.dynamic(SIGNED, DELTA, 1, 8 * K, RUNS))
    add("solo_paired_local", signed(lambda s: methods.solo_paired_triangles(s, 8 * K, runs=RUNS).local_), sql.dynamic(SIGNED, DELTA, 1, 8 * K, RUNS, True))
    add("pairing_conditional", signed(lambda s: methods.solo_paired_conditional(s, 8 * K, runs=RUNS).select("run", F.round("est", 6).alias("est"))), sql.conditional(SIGNED, DELTA, 8 * K, RUNS))
    add("pairing_conditional_ample", signed(lambda s: methods.solo_paired_conditional(s, 10**6).select(F.round("est", 6).alias("est"))), f"{sql.with_(SIGNED, sql.deletions(DELTA), sql._LIVES)} SELECT round(count(*) FILTER (died IS NULL), 6)::DOUBLE AS est FROM lv")
    add("coin_dynamic", signed(lambda s: methods.solo_coin_dynamic(s, Q, runs=RUNS).global_), sql.coin(SIGNED, Q, RUNS, delta=DELTA))
    add("quarantine", signed(lambda s: validated(s.unionByName(s.withColumn("seq", F.col("seq") + 10**9)))[1].select("u", "v").distinct()), f"{dele} SELECT u, v FROM d GROUP BY 1, 2 HAVING sum(sign) > 0")
    # measures, of the coin on one graph
    local = sql.coin(SMALL, Q, RUNS, True).removeprefix("WITH RECURSIVE ")
    glob = sql.coin(SMALL, Q, RUNS).removeprefix("WITH RECURSIVE ")
    truth, vertex = f"{sql.with_(SMALL, sql._TRIANGLES)} SELECT count(*) AS x FROM t", f"{sql.with_(SMALL, sql._LOCAL)} SELECT node, triangles AS x FROM x"
    est = f"(WITH RECURSIVE {glob})"
    both = f"SELECT a.run, a.node, x::DOUBLE AS x, coalesce(est, 0) AS e FROM (SELECT * FROM ({vertex}), range({RUNS}) AS r(run)) a LEFT JOIN (WITH RECURSIVE {local}) b ON a.node = b.node AND a.run = b.run"

    def measured(f: Callable[[DataFrame, methods.TriangleResult], DataFrame], name: str) -> Query:
        return on(SMALL, lambda e: f(e, methods.solo_coin_triangles(e, Q, runs=RUNS)).select(F.round(name, 6).alias(name)))

    add("metrics_mge", measured(lambda e, r: measures.mean_global_error(exact.exact_global(e), r.global_), "mge"), f"SELECT round(avg(abs(x - est) / (x + 1)), 6) AS mge FROM ({truth}), {est}")
    add("metrics_gvar", measured(lambda e, r: measures.global_variance(exact.exact_global(e), r.global_), "gvar"), f"SELECT round(avg((x - est) ** 2), 6) AS gvar FROM ({truth}), {est}")
    add("metrics_mle", measured(lambda e, r: measures.mean_local_error(exact.exact_local(e), r.local_, RUNS), "mle"), f"SELECT round(avg(m), 6) AS mle FROM (SELECT run, avg(abs(x - e) / (x + 1)) AS m FROM ({both}) GROUP BY 1)")
    add("metrics_pearson", measured(lambda e, r: measures.pearson_local(exact.exact_local(e), r.local_, RUNS), "pearson"), f"SELECT round(avg(r), 6) AS pearson FROM (SELECT run, corr(x, e) AS r FROM ({both}) GROUP BY 1)")
    rounded = lambda df: df.select([F.round(c, 4).alias(c) for c in df.columns])
    add("metrics_bias", on(SMALL, lambda e: rounded(measures.bias_report(exact.exact_global(e), methods.solo_coin_triangles(e, Q, runs=8).global_))),
        f"SELECT round(b, 4) AS bias, round(s, 4) AS stderr, round(b / s, 4) AS z, round(v, 4) AS sample_variance, round(b * b, 4) AS squared_bias FROM (SELECT avg(est) - max(x) AS b, stddev_samp(est) / sqrt(count(*)) AS s, var_samp(est) AS v FROM ({truth}), (WITH RECURSIVE {sql.coin(SMALL, Q, 8).removeprefix('WITH RECURSIVE ')}))")
    add("ratio_profile", on(SMALL, lambda e: measures.ratio_profile(adaptive(e).residency, routing.route_store(e, SHARDS))), f"{sql.with_(SMALL, *ada[:5])} SELECT run::INT AS run, held.shard::INT AS shard, count(*) AS held, any_value(storables) AS storables, count(*) / any_value(storables) AS ratio FROM held JOIN (SELECT shard, count(*) AS storables FROM s1 GROUP BY 1) c ON c.shard = held.shard WHERE exit_seq IS NULL GROUP BY 1, 2")
    # relational views
    g = "customer_overlap"
    sides = "SELECT a AS u, b AS v FROM t UNION SELECT b, c FROM t UNION SELECT a, c FROM t"
    add("closed_edges", on(g, relations.closed_edges), f"{sql.with_(g, sql._TRIANGLES)} {sides}")
    add("unclosed_edges", on(g, relations.open_edges), f"{sql.with_(g, sql._TRIANGLES)} SELECT u, v FROM e EXCEPT ({sides})")
    add("closed_nodes", on(g, relations.closed_nodes), f"{sql.with_(g, sql._TRIANGLES)} SELECT DISTINCT unnest([a, b, c]) AS node FROM t")
    add("induced_subgraph", _building, f"{sql.with_(g)} SELECT seq, u, v FROM e WHERE u IN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'BUILDING') AND v IN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'BUILDING')")
    add("degree_histogram", on(g, relations.degree_histogram), f"{sql.with_(g, sql._NODES)} SELECT degree, count(*) AS nodes FROM nd GROUP BY 1")
    add("mean_clustering", on(g, relations.mean_clustering), f"{sql.with_(g, sql._LOCAL)} SELECT round(avg(CASE WHEN degree > 1 THEN round(2 * triangles / (degree * (degree - 1)), 6) ELSE 0.0 END), 4) AS coefficient FROM x")
    add("edges_by_date", on(g, relations.edges_by_date), f"{sql.with_(g)} SELECT year(ts)::INT AS year, month(ts)::INT AS month, count(*) AS edges FROM p GROUP BY ROLLUP (year(ts)::INT, month(ts)::INT)")
    add("edge_rates_daily", on("user_handoff", lambda e: live.edge_rates(e, "1 day").select(F.date_format("start", "yyyy-MM-dd").alias("day"), "edges")), f"{sql.with_('user_handoff')} SELECT strftime(ts, '%Y-%m-%d') AS day, count(*) AS edges FROM p GROUP BY 1")
    half = sql.with_(SIGNED, sql.deletions(DELTA), "half AS (SELECT u, v FROM d WHERE seq < (SELECT count(*) // 2 FROM d) GROUP BY 1, 2 HAVING sum(sign) > 0)", "last AS (SELECT u, v FROM d GROUP BY 1, 2 HAVING sum(sign) > 0)")
    add("snapshot_kept", signed(lambda s: relations.kept_edges(s, s.count() // 2)), f"{half} SELECT * FROM half INTERSECT SELECT * FROM last")
    add("snapshot_lost", signed(lambda s: relations.lost_edges(s, s.count() // 2)), f"{half} SELECT * FROM half EXCEPT SELECT * FROM last")
    text = sql.adaptive(SMALL, SHARDS, K, T_STAR, None, RUNS)
    add("estimated_transitivity", on(SMALL, lambda e: relations.estimated_transitivity(e, adaptive(e).global_)), f"SELECT run, round(3 * est / w, 6) AS transitivity FROM ({text}), ({sql.with_(SMALL, sql._NODES)} SELECT sum(degree * (degree - 1) // 2) AS w FROM nd)")
    text = sql.adaptive(SMALL, SHARDS, K, T_STAR, None, RUNS, True)
    add("top_estimated", on(SMALL, lambda e: relations.top_estimated(adaptive(e).local_, 20)), f"SELECT node, est FROM ({text}) WHERE run = 0 ORDER BY est DESC, node LIMIT 20")
    # other surfaces of the estimators
    text = sql.adaptive(SMALL, SHARDS, K, T_STAR, None, 1)
    add("sql_adaptive_global", on(SMALL, lambda e: sql_surface.adaptive_by_sql(e, SHARDS, K, FLOOR)), text)
    add("stream_adaptive_global", on(SMALL, lambda e: _streamed(e, lambda s: live.adaptive_stream(s, SHARDS, K, FLOOR), K * K * (K - 1))), f"SELECT est FROM ({text})")
    add("stream_dynamic_ample", signed(lambda s: _streamed(s, lambda x: live.dynamic_stream(x, SHARDS, 10**6), 10**6 * (10**6 - 1))), f"{sql.with_(SIGNED, sql.deletions(DELTA), sql._LIVES)} SELECT count(*) FILTER (died IS NULL)::DOUBLE AS est FROM lv")
    # experiments
    add("w1_improvement", trial(["customer_overlap"], lambda e, g: measures.improvement(workloads.accuracy(e, "customer_overlap", shares=(0.05,), runs=3, local=False), "solo_coin", "adaptive", "mge", ["graph", "setting"])))
    add("w1_accuracy", trial(ACCURACY, lambda e, g: workloads.accuracy(e, g, shares=(1e-5, 1e-4, 1e-3, 1e-2, 1e-1), runs=10)))
    add("w2_speed", on("customer_overlap", lambda e: workloads.speed(e, "customer_overlap", share=0.01)))
    add("w3_floor", trial(["customer_overlap"], lambda e, g: workloads.floors(e, "customer_overlap", ratio_floors=(0.00032, 0.0032, 0.032, 0.1, 0.2), shares=(0.005, 0.02), runs=10)))
    add("w4_dynamic_accuracy", trial(graphs.GRAPHS, lambda e, g: workloads.dynamic_accuracy(e, g, share=0.01, n_shards=30, runs=10)))
    add("w5_dynamic_speed", on("page_links", lambda e: workloads.dynamic_speed(e, "page_links", share=0.01, solo=(0.01, 0.05))))
    add("w6_shards", trial(SHARD_SWEEP, lambda e, g: workloads.shard_sweep(e, g, shards=(10, 50, 90, 130), runs=10)))
    add("w7_scaling", on("customer_overlap", lambda e: workloads.scaling(e, "customer_overlap")))
    return out


def _building(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The co-purchase graph of one market segment's customers."""
    some = graphs.read_table(spark, sf_dir, "customer").where("c_mktsegment = 'BUILDING'").select(F.col("c_custkey").alias("node"))
    return relations.induced(_graph(spark, sf_dir, "customer_overlap").select("seq", "u", "v"), some)


def _streamed(events: DataFrame, estimator: Callable[[DataFrame], DataFrame], den: int, arrivals: int = 3) -> DataFrame:
    """(est) of a live estimator that gets the events in several arrivals, by way of files and a sink in the shared folder."""
    spark, folder = events.sparkSession, fresh_folder(events.sparkSession, "live")
    n = events.count()
    for i in range(arrivals):
        own = events.where((F.col("seq") >= n * i // arrivals) & (F.col("seq") < n * (i + 1) // arrivals))
        own.select("seq", "ts", "u", "v", "sign").coalesce(1).write.mode("append").parquet(f"{folder}/in")
    rows = estimator(file_edges(spark, f"{folder}/in"))
    rows.writeStream.outputMode("update").foreachBatch(latest_sink(f"{folder}/out")).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
    return live.collected(latest(spark, f"{folder}/out", ["shard"]), den)


def _replayed(events: DataFrame) -> DataFrame:
    """(relational, replayed, differing): hits of the plan, of the state machines, and in one of them only."""
    cols = ["shard", "seq", "u", "v", "c", "kind", "num"]
    a = cut(methods.adaptive_triangles(events, SHARDS, K, FLOOR).hits.select(cols))
    b = cut(replay.adaptive_replay(events, SHARDS, K, FLOOR).select(cols))
    n = lambda df, name: df.agg(F.count(F.lit(1)).alias(name))
    return n(a, "relational").join(n(b, "replayed"), F.lit(True)).join(n(a.exceptAll(b).unionByName(b.exceptAll(a)), "differing"), F.lit(True))


def _rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    local = exact.exact_local(_graph(spark, sf_dir, "customer_overlap"))
    read = partial(graphs.read_table, spark, sf_dir)
    rows = local.join(read("customer"), F.col("node") == F.col("c_custkey")).join(read("nation"), F.col("n_nationkey") == F.col("c_nationkey")).join(read("region"), F.col("r_regionkey") == F.col("n_regionkey"))
    return rows.rollup(F.col("r_name").alias("region"), F.col("n_name").alias("nation")).agg(F.sum("triangles").alias("triangles"))


def _labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    local = exact.exact_local(_graph(spark, sf_dir, "doc_near_copies"))
    labels = graphs.read_table(spark, sf_dir, "labels")
    return local.join(labels, F.col("node") == F.col("doc_id")).groupBy("quality").agg(F.count(F.lit(1)).alias("docs"), F.sum("triangles").alias("triangles"))


def queries() -> dict[str, Query]:
    return {name: make for name, (make, _) in _found().items()}


def oracle_sql() -> dict[str, str]:
    return {name: text for name, (_, text) in _found().items() if text}


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The adaptive pool on the co-purchase graph."""
    events = _graph(spark, sf_dir, "part_copurchase")
    return methods.adaptive_triangles(events, 4, 500, FLOOR).global_


"""DuckDB SQL for the queries: the same results from the same tables, by SQL alone."""

from __future__ import annotations


def h60(*parts: str) -> str:
    """The portable 60-bit number of md5 of the parts, joined by bars."""
    return f"('0x' || substr(md5({" || '|' || ".join(f'({p})::VARCHAR' for p in parts)}), 1, 15))::BIGINT"


_LINES = "l AS (SELECT l_orderkey, l_partkey, l_suppkey, o_custkey, o_orderdate AS ts FROM lineitem JOIN orders ON l_orderkey = o_orderkey)"
_LINKS = """k AS (SELECT page_id, regexp_extract(url, '://([^/]*)', 1) AS host, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages)"""


def _pairs(key: str, item: str, source: str, ts: str = "ts") -> str:
    return f"""own AS (SELECT DISTINCT {key} AS k, {item} AS a, {ts} AS ts FROM {source}),
      p AS (SELECT x.a AS u, y.a AS v, min(x.ts) AS ts FROM own x JOIN (SELECT DISTINCT k, a FROM own) y ON x.k = y.k AND x.a < y.a GROUP BY 1, 2)"""


def _numbered(order: str) -> str:
    return f"e AS (SELECT row_number() OVER (ORDER BY {order}, u, v) - 1 AS seq, u::BIGINT AS u, v::BIGINT AS v FROM p)"


#: Common table expressions up to e(seq, u, v), by graph.
EDGES = {
    "part_copurchase": f"{_LINES}, {_pairs('l_orderkey', 'l_partkey', 'l')}, {_numbered('ts')}",
    "supplier_cosupply": f"{_LINES}, {_pairs('l_orderkey', 'l_suppkey', 'l')}, {_numbered('ts')}",
    "trade_triads": f"""{_LINES}, i AS (SELECT o_custkey * 4 AS c, l_partkey * 4 + 1 AS p, l_suppkey * 4 + 2 AS s, ts FROM l),
      r AS (SELECT c AS a, p AS b, ts FROM i UNION ALL SELECT p, s, ts FROM i UNION ALL SELECT c, s, ts FROM i),
      p AS (SELECT least(a, b) AS u, greatest(a, b) AS v, min(ts) AS ts FROM r GROUP BY 1, 2), {_numbered('ts')}""",
    "customer_overlap": f"""{_LINES}, m AS (SELECT *, date_trunc('month', ts) AS month FROM l), {_pairs("l_partkey || '|' || month", 'o_custkey', 'm', 'month')}, {_numbered(h60("'order'", 'u', 'v'))}""",
    "user_handoff": f"""w AS (SELECT ts, event_id, user_id AS b, lag(user_id) OVER (ORDER BY ts, event_id) AS a FROM events),
      p AS (SELECT least(a, b) AS u, greatest(a, b) AS v, min(ts) AS ts, min(event_id) AS id FROM w WHERE a <> b GROUP BY 1, 2), {_numbered('ts, id')}""",
    "page_links": f"""{_LINKS}, n AS (SELECT page_id, 'p' || page_id AS p, 'h' || host AS h, 'l' || href AS l FROM k),
      s AS (SELECT page_id, p AS x, h AS y FROM n UNION SELECT page_id, p, l FROM n UNION SELECT page_id, h, l FROM n),
      ids AS (SELECT name, row_number() OVER (ORDER BY name) - 1 AS node FROM (SELECT x AS name FROM s UNION SELECT y FROM s)),
      p AS (SELECT least(a.node, b.node) AS u, greatest(a.node, b.node) AS v, min(page_id) AS ts FROM s JOIN ids a ON a.name = x JOIN ids b ON b.name = y WHERE x <> y GROUP BY 1, 2), {_numbered('ts')}""",
    "page_overlap": f"{_LINKS}, {_pairs('href', 'page_id', 'k', '0')}, {_numbered('v')}",
    "doc_near_copies": f"""n AS (SELECT DISTINCT doc_id, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 40),
      r AS (SELECT doc_id, line, row_number() OVER (PARTITION BY line ORDER BY doc_id) AS k FROM n),
      p AS (SELECT DISTINCT x.doc_id AS u, y.doc_id AS v FROM r x JOIN r y ON x.line = y.line AND y.k > x.k AND y.k <= x.k + 8), {_numbered('v')}""",
    "vector_neighbours": f"""p AS (SELECT x.vec_id AS u, y.vec_id AS v FROM embeddings x, embeddings y WHERE x.vec_id < y.vec_id
      AND list_cosine_similarity(x.embedding::DOUBLE[], y.embedding::DOUBLE[]) > 0.3), {_numbered('u')}""",
}

_TRIANGLES = "t AS (SELECT a.u AS a, a.v AS b, b.v AS c FROM e a JOIN e b ON a.v = b.u JOIN e c ON c.u = a.u AND c.v = b.v)"
_NODES = "nd AS (SELECT node, count(*) AS degree FROM (SELECT u AS node FROM e UNION ALL SELECT v FROM e) GROUP BY 1)"
_LOCAL = f"{_TRIANGLES}, {_NODES}, c AS (SELECT node, count(*) AS triangles FROM (SELECT unnest([a, b, c]) AS node FROM t) GROUP BY 1), x AS (SELECT nd.node, degree, coalesce(triangles, 0) AS triangles FROM nd LEFT JOIN c USING (node))"


def with_(graph: str, *more: str) -> str:
    return "WITH RECURSIVE " + ",\n".join([EDGES[graph], *[m for m in more if m]])


def deletions(delta: float, seed: int = 42) -> str:
    """d(seq, u, v, sign) from e."""
    return f"""tot AS (SELECT count(*) AS n FROM e),
      ch AS (SELECT seq, u, v, row_number() OVER (ORDER BY {h60(str(seed), "'chosen'", 'u', 'v')}, u, v) AS r FROM e),
      al AS (SELECT seq AS pos, 1 AS kind, u, v, 1 AS sign FROM e UNION ALL
             SELECT seq + 1 + {h60(str(seed), "'place'", 'u', 'v')} % (n - seq), 0, u, v, -1 FROM ch, tot WHERE r <= floor({delta} * n)),
      d AS (SELECT row_number() OVER (ORDER BY pos, kind, u, v) - 1 AS seq, u, v, sign FROM al)"""


_LIFE = "li AS (SELECT u, v, seq AS i, x AS o FROM (SELECT *, lead(seq) OVER (PARTITION BY u, v ORDER BY seq) AS x FROM d) WHERE sign = 1)"
_LIVES = f"""{_LIFE}, tl AS (SELECT a.u AS a, a.v AS b, b.v AS c, greatest(a.i, b.i, c.i) AS born, least(a.o, b.o, c.o) AS died
      FROM li a JOIN li b ON a.v = b.u JOIN li c ON c.u = a.u AND c.v = b.v),
      lv AS (SELECT * FROM tl WHERE died IS NULL OR born < died)"""


def stored(events: str, shards: int, runs: int, seed: int = 42) -> str:
    """h(…, h_u, h_v) of the events and st(run, shard, seq, u, v, sign, n, key): copies at the shards that may store them."""
    hu, hv = h60(str(seed), "u"), h60(str(seed), "v")
    return f"""h AS (SELECT *, {hu} % {shards} AS h_u, {hv} % {shards} AS h_v FROM {events}),
      s0 AS (SELECT seq, u, v, sign, h_u AS shard FROM h UNION SELECT seq, u, v, sign, h_v FROM h),
      s1 AS (SELECT *, row_number() OVER (PARTITION BY shard ORDER BY seq) AS n FROM s0),
      st AS (SELECT run, shard, seq, u, v, sign, n, {h60(str(seed), 'run', 'shard', 'seq', 'u', 'v')} AS key FROM s1, range({runs}) AS r(run))"""


def reservoir(source: str, group: str, k: int, name: str) -> str:
    """name(source columns, exit_seq) of what enters the bottom k of each group; source has seq, key and the group's columns."""
    same = " AND ".join(f"a.{g} = b.{g}" for g in group.split(", "))
    cols = ", ".join(f"a.{g}" for g in group.split(", "))
    return f"""{name}_e AS (SELECT * FROM (SELECT a.*, (SELECT count(*) FROM {source} b WHERE {same} AND b.seq < a.seq AND b.key < a.key) AS rk FROM {source} a) WHERE rk < {k}),
      {name}_x AS (SELECT {cols}, a.seq, b.seq AS exit_seq, row_number() OVER (PARTITION BY {cols}, a.seq ORDER BY b.seq) AS j, a.rk FROM {name}_e a JOIN {name}_e b ON {same} AND b.seq > a.seq AND b.key < a.key),
      {name} AS (SELECT a.*, b.exit_seq FROM {name}_e a LEFT JOIN (SELECT * FROM {name}_x WHERE j = {k} - rk) b ON {same} AND a.seq = b.seq)"""


def hits(events: str, held: str, shards: int, seed: int = 42) -> str:
    """hi(run, shard, seq, sign, u, v, c, seg_a, seg_b); held has run, shard, segment, u, v, enter_seq, exit_seq."""
    hc = h60(str(seed), "a.y")
    return f"""bo AS (SELECT run, shard, segment, u AS x, v AS y, enter_seq, exit_seq FROM {held} UNION ALL SELECT run, shard, segment, v, u, enter_seq, exit_seq FROM {held}),
      hi AS (SELECT a.run, a.shard, e.seq, e.sign, e.u, e.v, a.y AS c, a.segment AS seg_a, b.segment AS seg_b
        FROM {events} e JOIN bo a ON a.x = e.u JOIN bo b ON b.x = e.v AND b.y = a.y AND b.run = a.run AND b.shard = a.shard
        WHERE a.enter_seq < e.seq AND (a.exit_seq IS NULL OR a.exit_seq >= e.seq) AND b.enter_seq < e.seq AND (b.exit_seq IS NULL OR b.exit_seq >= e.seq)
          AND a.shard = CASE WHEN h_u = h_v THEN h_u ELSE {hc} % {shards} END)"""


def _fixed(t: str, k: int) -> str:
    return f"(CASE WHEN {t} > {k} THEN {t}::HUGEINT * ({t} - 1) ELSE {k * (k - 1)} END)"


def _summed(local: bool, den: int, runs: int) -> str:
    if local:
        return f"SELECT run::INT AS run, node, sum(num * sign)::DOUBLE / {float(den)} AS est FROM (SELECT run, sign, num, unnest([u, v, c]) AS node FROM w) GROUP BY 1, 2"
    return f"SELECT r.run::INT AS run, coalesce(sum(num * sign)::DOUBLE / {float(den)}, 0.0) AS est FROM range({runs}) AS r(run) LEFT JOIN w ON w.run = r.run GROUP BY 1"


def sharded(graph: str, shards: int, k: int, runs: int, local: bool = False) -> str:
    ctes = [
        "ev AS (SELECT *, 1 AS sign FROM e)", stored("ev", shards, runs), reservoir("st", "run, shard", k, "rs"), "held AS (SELECT run, shard, 0 AS segment, u, v, seq AS enter_seq, exit_seq FROM rs)", hits("h", "held", shards),
        "b AS (SELECT hi.*, coalesce((SELECT count(*) FROM s1 WHERE s1.shard = hi.shard AND s1.seq < hi.seq), 0) AS t FROM hi)", f"w AS (SELECT *, {_fixed('t', k)} AS num FROM b)",
    ]
    return f"{with_(graph, *ctes)} {_summed(local, k * (k - 1), runs)}"


def adaptive_ctes(shards: int, k: int, t_star: int, sets: int | None, runs: int) -> list[str]:
    segment = "((n - 1) // {0})".format(t_star)
    segment = segment if sets is None else f"least({segment}, {sets - 1})"
    open_ = f"(b // {t_star})" if sets is None else f"least(b // {t_star}, {sets - 1})"
    return [
        "ev AS (SELECT *, 1 AS sign FROM e)", stored("ev", shards, runs), f"sg AS (SELECT *, {segment} AS segment FROM st)", reservoir("sg", "run, shard, segment", k, "rs"),
        "held AS (SELECT run, shard, segment, u, v, seq AS enter_seq, exit_seq FROM rs)", hits("h", "held", shards),
        "bb AS (SELECT hi.*, (SELECT count(*) FROM s1 WHERE s1.shard = hi.shard AND s1.seq < hi.seq) AS b FROM hi)",
        f"oo AS (SELECT *, {open_} AS o, b - {open_} * {t_star} AS t FROM bb)",
        "kk AS (SELECT *, CASE WHEN seg_a = o AND seg_b = o THEN 1 WHEN seg_a = o OR seg_b = o THEN 4 WHEN seg_a = seg_b THEN 2 ELSE 3 END AS kind FROM oo)",
        f"w AS (SELECT *, CASE kind WHEN 1 THEN {k}::HUGEINT * {_fixed('t', k)} WHEN 2 THEN {k * t_star * (t_star - 1)} WHEN 3 THEN {(k - 1) * t_star**2} ELSE {(k - 1) * t_star}::HUGEINT * greatest(t, {k}) END AS num FROM kk)",
    ]


def adaptive(graph: str, shards: int, k: int, t_star: int, sets: int | None, runs: int, local: bool = False) -> str:
    return f"{with_(graph, *adaptive_ctes(shards, k, t_star, sets, runs))} {_summed(local, k * k * (k - 1), runs)}"


def dynamic_ctes(delta: float, shards: int, k: int, runs: int, seed: int = 42) -> list[str]:
    """Random pairing with first vacated, first filled slots; chains of reuse by recursion."""
    return [
        deletions(delta), stored("d", shards, 1), "q0 AS (SELECT *, sum(-sign) OVER (PARTITION BY shard ORDER BY seq) AS wv FROM s1)",
        "q1 AS (SELECT *, sign = 1 AND wv < least(0, coalesce(min(wv) OVER (PARTITION BY shard ORDER BY seq ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) AS fresh, lead(seq) OVER (PARTITION BY shard, u, v ORDER BY seq) AS nx FROM q0)",
        "q2 AS (SELECT *, sum((sign = 1 AND NOT fresh)::INT) OVER (PARTITION BY shard ORDER BY seq) AS re, sum((sign = -1)::INT) OVER (PARTITION BY shard ORDER BY seq) AS va FROM q1)",
        "par AS (SELECT i.shard, i.seq, o.seq AS parent FROM q2 i JOIN q2 x ON x.shard = i.shard AND x.sign = -1 AND x.va = i.re JOIN q2 o ON o.shard = x.shard AND o.sign = 1 AND o.nx = x.seq WHERE i.sign = 1 AND NOT i.fresh)",
        "ro AS (SELECT shard, seq, -wv AS slot FROM q2 WHERE fresh UNION ALL SELECT par.shard, par.seq, ro.slot FROM ro JOIN par ON par.shard = ro.shard AND par.parent = ro.seq)",
        f"fr AS (SELECT run, shard, -wv AS slot, seq, {h60(str(seed), 'run', 'shard', '-wv', '0', '0')} AS key FROM q2, range({runs}) AS r(run) WHERE fresh)", reservoir("fr", "run, shard", k, "rs"),
        """held AS (SELECT rs.run, rs.shard, 0 AS segment, q2.u, q2.v, q2.seq AS enter_seq, least(q2.nx, rs.exit_seq) AS exit_seq
           FROM rs JOIN ro ON ro.shard = rs.shard AND ro.slot = rs.slot JOIN q2 ON q2.shard = ro.shard AND q2.seq = ro.seq WHERE rs.exit_seq IS NULL OR rs.exit_seq > q2.seq)""",
        hits("h", "held", shards), "b AS (SELECT hi.*, (SELECT count(*) FROM q2 WHERE q2.shard = hi.shard AND fresh AND q2.seq < hi.seq) AS t FROM hi)", f"w AS (SELECT *, {_fixed('t', k)} AS num FROM b)",
    ]


def dynamic(graph: str, delta: float, shards: int, k: int, runs: int, local: bool = False, seed: int = 42) -> str:
    return f"{with_(graph, *dynamic_ctes(delta, shards, k, runs, seed))} {_summed(local, k * (k - 1), runs)}"


def conditional(graph: str, delta: float, k: int, runs: int) -> str:
    """Random pairing on one machine, by the triangles of the final sample alone."""
    lc = "(lgamma({0} + 1) - lgamma({1} + 1) - lgamma({0} - {1} + 1))".format
    terms = " + ".join(f"CASE WHEN {j} <= s AND room - {j} BETWEEN 0 AND d THEN exp({lc('s', str(j))} + {lc('d', f'(room - {j})')} - {lc('(s + d)', 'room')}) ELSE 0 END" for j in range(3))
    ctes = dynamic_ctes(delta, 1, k, runs)[:-3]
    ctes += [
        "fin AS (SELECT run, u, v FROM held WHERE exit_seq IS NULL)", "ta AS (SELECT a.run, count(*) AS tau FROM fin a JOIN fin b ON a.run = b.run AND a.v = b.u JOIN fin c ON c.run = a.run AND c.u = a.u AND c.v = b.v GROUP BY 1)",
        "ys AS (SELECT run, count(*)::DOUBLE AS y FROM fin GROUP BY 1)", "sd AS (SELECT count(*) FILTER (sign = 1 AND nx IS NULL) AS s, (SELECT coalesce(max(slot), 0) FROM ro) AS opened FROM q2)",
        f"ro2 AS (SELECT s::DOUBLE AS s, (opened - s)::DOUBLE AS d, least({k}, opened)::DOUBLE AS room FROM sd)",
        f"ka AS (SELECT *, CASE WHEN d >= room - 2 AND s + d >= 3 THEN 1 - ({terms}) ELSE 1.0 END AS kappa FROM ro2)",
    ]
    return f"{with_(graph, *ctes)} SELECT r.run::INT AS run, round(CASE WHEN coalesce(y, 0) >= 3 THEN coalesce(tau, 0) / kappa * (s * (s - 1) * (s - 2)) / (y * (y - 1) * (y - 2)) ELSE 0.0 END, 6) AS est FROM range({runs}) AS r(run) LEFT JOIN ys ON ys.run = r.run LEFT JOIN ta ON ta.run = r.run, ka"


def recency(graph: str, k: int, runs: int, alpha: float = 0.5, seed: int = 42) -> str:
    """The newest edges and a reservoir of those that left them."""
    newest = int(alpha * k)
    rest = k - newest
    ctes = [
        "ev AS (SELECT *, 1 AS sign, 0 AS h_u, 0 AS h_v FROM e)", "tt AS (SELECT count(*) AS total FROM e)", f"old AS (SELECT u, v, seq, seq + {newest} AS leaves, run FROM e, range({runs}) AS r(run))",
        f"ag AS (SELECT run, 0 AS shard, 0 AS segment, u, v, leaves AS seq, {h60(str(seed), 'run', '0', 'leaves', 'u', 'v')} AS key FROM old, tt WHERE leaves < total)", reservoir("ag", "run, shard, segment", rest, "rs"),
        "held AS (SELECT run, 0 AS shard, -1 AS segment, u, v, seq AS enter_seq, CASE WHEN leaves < total THEN leaves END AS exit_seq FROM old, tt UNION ALL SELECT run, shard, segment, u, v, seq, exit_seq FROM rs)", hits("ev", "held", 1),
        f"kk AS (SELECT *, (seg_a = 0)::INT + (seg_b = 0)::INT AS n_old, greatest(seq - {newest}, 0) AS t FROM hi)",
        f"w AS (SELECT *, CASE n_old WHEN 0 THEN {rest * (rest - 1)}::HUGEINT WHEN 1 THEN greatest(t, {rest})::HUGEINT * {rest - 1} ELSE {_fixed('t', rest)} END AS num FROM kk)",
    ]
    return f"{with_(graph, *ctes)} {_summed(False, rest * (rest - 1), runs)}"


def coin(graph: str, q: float, runs: int, local: bool = False, delta: float | None = None, seed: int = 42, conditional: bool = False) -> str:
    ctes = [deletions(delta) if delta is not None else "d AS (SELECT seq, u, v, 1 AS sign FROM e)", _LIFE, "h AS (SELECT *, 0 AS h_u, 0 AS h_v FROM d)"]
    key = h60(str(seed), "run", "0", "i", "u", "v")
    ctes += [f"held AS (SELECT run, 0 AS shard, 0 AS segment, u, v, i AS enter_seq, o AS exit_seq FROM li, range({runs}) AS r(run) WHERE {key} < {int(q * 2**60)})", hits("h", "held", 1)]
    own = "JOIN (SELECT run, u, v, enter_seq AS seq FROM held UNION SELECT run, u, v, exit_seq FROM held WHERE exit_seq IS NOT NULL) USING (run, u, v, seq)" if conditional else ""
    ctes.append(f"w AS (SELECT *, 1 AS num FROM hi {own})")
    return f"{with_(graph, *ctes)} {_summed(local, q**3 if conditional else q**2, runs)}"

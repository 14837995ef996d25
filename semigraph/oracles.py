"""SQL twins of the registered queries, in DuckDB's dialect over the given tables."""

from __future__ import annotations

COP = """op AS (SELECT DISTINCT l_orderkey o, l_partkey p FROM lineitem),
cop AS (SELECT a.p i, b.p j, count(*)::BIGINT v FROM op a JOIN op b ON a.o = b.o AND a.p <> b.p GROUP BY 1, 2)"""
COP2 = COP + ", cop2 AS (SELECT * FROM cop WHERE v >= 2)"
VEC = "x AS (SELECT p_partkey i, p_partkey % 5 + 1 v FROM part WHERE p_partkey % 4 = 0)"
MASK = "m AS (SELECT p_partkey i FROM part WHERE p_partkey % 3 = 0)"
WEIGHTED = COP + ", w AS (SELECT i, j, (least(i, j) * 31 + greatest(i, j) * 17) % 64 + 1 v FROM cop)"
CHAIN = """e0 AS (SELECT event_id i, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) j FROM events),
chain AS (SELECT i, j FROM e0 WHERE j IS NOT NULL UNION ALL SELECT j, i FROM e0 WHERE j IS NOT NULL)"""
GEO = """g0 AS (SELECT n_regionkey::BIGINT i, n_nationkey::BIGINT + 10 j FROM nation UNION ALL SELECT c_nationkey::BIGINT + 10, c_custkey * 2 + 100 FROM customer
UNION ALL SELECT s_nationkey::BIGINT + 10, s_suppkey * 2 + 101 FROM supplier),
geo AS (SELECT i, j, 1::BIGINT v FROM g0 UNION ALL SELECT j, i, 1::BIGINT FROM g0)"""
CUSTPART = "cp AS (SELECT o_custkey i, l_partkey j, sum(l_quantity)::BIGINT v FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1, 2)"
USERKEY = "uk AS (SELECT user_id i, (props->>'$.k')::BIGINT j, count(*)::BIGINT v FROM events GROUP BY 1, 2)"
WEB = """web AS (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) href FROM pages)"""
LINES = r"""l0 AS (SELECT DISTINCT doc_id, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) line FROM documents) WHERE length(line) >= 40),
dl AS (SELECT * FROM l0 WHERE line IN (SELECT line FROM l0 GROUP BY 1 HAVING count(*) > 1))"""
CONV = "conv AS (SELECT a.conv_id * 8 + a.turn i, b.conv_id * 8 + b.turn j, 1::BIGINT v FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1)"


def rmat(scale: int = 10, ef: int = 16) -> str:
    parts = [f"r0 AS (SELECT (range * 2654435761 + 42) % 2147483648 x, 0::BIGINT i, 0::BIGINT j FROM range({ef << scale}))"]
    for k in range(scale):
        r = "((x // 65536) % 100)"
        parts.append(f"r{k + 1} AS (SELECT (x * 1103515245 + 12345) % 2147483648 x, i * 2 + ({r} >= 76)::BIGINT i, j * 2 + ({r} >= 57 AND {r} < 76 OR {r} >= 95)::BIGINT j FROM r{k})")
    return ", ".join(parts) + f", rmat AS (SELECT DISTINCT i, j, 1::BIGINT v FROM (SELECT i, j FROM r{scale} WHERE i <> j UNION ALL SELECT j, i FROM r{scale} WHERE i <> j))"


def order_rmat(scale: int = 10, share: int = 1) -> str:
    """The same from the keys of orders, every share-th."""
    first = f"FROM (SELECT o_orderkey // {share} range FROM orders WHERE o_orderkey % {share} = 0))"
    return rmat(scale).replace(f"FROM range({16 << scale}))", first, 1)


def levels(edges: str, name: str, source: str, cap: int, where: str = "") -> str:
    return f"""WITH RECURSIVE {edges}, lv AS (SELECT {source} i, 1::BIGINT v UNION SELECT e.j, lv.v + 1 FROM lv JOIN {name} e ON e.i = lv.i WHERE lv.v < {cap})
SELECT i, min(v) v FROM lv {where} GROUP BY i"""


def reach(edges: str, name: str, keep: str = "") -> str:
    return f"""WITH RECURSIVE {edges}, rc AS (SELECT DISTINCT i, i k FROM {name} UNION SELECT rc.i, e.j FROM rc JOIN {name} e ON e.i = rc.k)
SELECT i, min(k) v FROM rc {keep} GROUP BY i"""


def pagerank(rounds: int, tail: str = "SELECT i, round(v, 9) v FROM p{k}", edges: str = COP, name: str = "cop", vertices: str = "SELECT p_partkey i FROM part") -> str:
    parts = [edges, f"vs AS ({vertices})", f"deg AS (SELECT i, count(*) d FROM {name} GROUP BY 1)", "n AS (SELECT count(*)::DOUBLE n FROM vs)", "p0 AS (SELECT i, 1 / (SELECT n FROM n) v FROM vs)"]
    for k in range(rounds):
        parts.append(f"""y{k} AS (SELECT e.j i, sum(p.v / d) y FROM {name} e JOIN p{k} p ON p.i = e.i JOIN deg ON deg.i = e.i GROUP BY 1),
h{k} AS (SELECT coalesce(sum(v), 0) h FROM p{k} p WHERE NOT EXISTS (SELECT 1 FROM deg WHERE deg.i = p.i)),
p{k + 1} AS (SELECT p.i, 0.15 / (SELECT n FROM n) + 0.85 * (coalesce(y, 0) + (SELECT h FROM h{k}) / (SELECT n FROM n)) v FROM p{k} p LEFT JOIN y{k} y ON y.i = p.i)""")
    return "WITH " + ", ".join(parts) + " " + tail.format(k=rounds)


def semiring(add: str, mul: str) -> str:
    return f"WITH {COP}, {VEC} SELECT cop.i, {add}({mul}) v FROM cop JOIN x ON x.i = cop.j GROUP BY 1"


def over(f: str, table: str = "cop") -> str:
    return f"WITH {COP2} SELECT i, {f} v FROM {table} GROUP BY 1"


MXV = f"WITH {COP}, {VEC}, {MASK} SELECT cop.i, sum(cop.v * x.v)::BIGINT v FROM cop JOIN x ON x.i = cop.j"
TRI = f"WITH {COP}, l AS (SELECT i, j FROM cop WHERE i > j) SELECT count(*)::BIGINT triangles FROM l a JOIN l b ON a.j = b.j AND b.i < a.i JOIN l c ON c.i = a.i AND c.j = b.i"
PER = "t AS (SELECT a.i, count(*) // 2 t FROM cop a JOIN cop b ON b.i = a.j JOIN cop c ON c.i = a.i AND c.j = b.j GROUP BY 1)"
BFS = levels(COP, "cop", "0::BIGINT", 6)
SSSP = f"""WITH RECURSIVE {WEIGHTED}, s AS (SELECT 0::BIGINT i, 0::BIGINT v UNION SELECT e.j, s.v + e.v FROM s JOIN w e ON e.i = s.i WHERE s.v + e.v <= 24)
SELECT i, min(v) v FROM s GROUP BY i"""
# All distances: a vertex is reached again only by a shorter path.
SSSP_ALL = f"""WITH RECURSIVE {WEIGHTED}, s(i, v) USING KEY (i) AS (SELECT 0::BIGINT, 0::BIGINT UNION SELECT e.j, min(s.v + e.v) FROM s JOIN w e ON e.i = s.i LEFT JOIN recurring.s r ON r.i = e.j WHERE r.v IS NULL OR s.v + e.v < r.v GROUP BY e.j)
SELECT i, v FROM s"""
CC_CHAIN = f"WITH {CHAIN}, of AS (SELECT event_id i, min(event_id) OVER (PARTITION BY user_id) v FROM events) SELECT i, v FROM of WHERE i IN (SELECT i FROM chain)"
MASKED_PAIR = f"WITH {COP2} SELECT a.i, b.j, count(*)::BIGINT v FROM cop a JOIN cop b ON b.i = a.j JOIN cop2 m ON m.i = a.i AND m.j = b.j GROUP BY 1, 2"
SPMM = f"WITH {CUSTPART} SELECT i, " + ", ".join(f"sum(v * ((j * {k + 3}) % 7))::BIGINT v{k}" for k in range(4)) + " FROM cp GROUP BY 1"
TRACE_ROWS = f"""WITH RECURSIVE {COP}, lv AS (SELECT 0::BIGINT i, 1::BIGINT v UNION SELECT e.j, lv.v + 1 FROM lv JOIN cop e ON e.i = lv.i WHERE lv.v < 6),
d AS (SELECT i, min(v) v FROM lv GROUP BY 1), s AS (SELECT v AS round, count(*)::BIGINT frontier FROM d GROUP BY 1)"""

SQL: dict[str, str] = {
    "build_dup": "SELECT l_suppkey i, l_partkey j, sum(l_linenumber)::BIGINT v FROM lineitem GROUP BY 1, 2",
    "nvals": f"WITH {COP} SELECT count(*)::BIGINT n FROM cop",
    "tuples": f"WITH {COP2} SELECT i, j, v FROM cop2",
    "ewise_mult_v": "SELECT p_partkey i, (p_partkey % 5 + 1) * (p_partkey % 5 + 1) v FROM part WHERE p_partkey % 12 = 0",
    "ewise_add_v": "SELECT p_partkey i, (p_partkey % 5 + 1) * ((p_partkey % 4 = 0)::BIGINT + (p_partkey % 6 = 0)::BIGINT) v FROM part WHERE p_partkey % 4 = 0 OR p_partkey % 6 = 0",
    "ewise_mult_m": f"WITH {COP2} SELECT i, j, 2 * v v FROM cop2",
    "ewise_add_m": f"WITH {COP} SELECT i, j, v FROM cop",
    "ewise_rank_row": f"WITH {COP2} SELECT i, j, v * (i % 5 + 1) v FROM cop2 WHERE i % 2 = 0",
    "ewise_rank_col": f"WITH {COP2} SELECT i, j, v + (j % 5 + 1) v FROM cop2 WHERE j % 2 = 0",
    "ewise_rank_scalar": f"WITH {COP2} SELECT i, j, v * 10 v FROM cop2",
    "extract_sub": f"WITH {COP} SELECT i // 2 i, j // 3 j, v FROM cop WHERE i % 2 = 0 AND i < 100 AND j % 3 = 0 AND j < 90",
    "gather": f"WITH {VEC} SELECT p_partkey i, x.v FROM part JOIN x ON x.i = p_partkey * 7 % 200",
    "scatter_min": f"WITH {VEC} SELECT x.i * 7 % 50 i, min(v) v FROM x GROUP BY 1",
    "assign_const": "SELECT p_partkey i, 9::BIGINT v FROM part",
    "assign_masked": f"WITH {VEC} SELECT p_partkey i, CASE WHEN p_partkey % 3 = 0 THEN 9 ELSE x.v END v FROM part LEFT JOIN x ON x.i = p_partkey WHERE p_partkey % 3 = 0 OR x.v IS NOT NULL",
    "apply": f"WITH {VEC} SELECT i, v * v + 1 v FROM x",
    "reduce_rows": over("sum(v)::BIGINT"),
    "reduce_cols": f"WITH {CUSTPART} SELECT j i, sum(v)::BIGINT v FROM cp GROUP BY 1",
    "reduce_scalar": f"WITH {COP} SELECT sum(v)::BIGINT v FROM cop",
    "degrees": over("count(*)::BIGINT"),
    "transpose": f"WITH {CUSTPART} SELECT j i, i j, v FROM cp",
    "tril": f"WITH {COP2} SELECT i, j, v FROM cop2 WHERE i > j",
    "degree_relabel": f"WITH {COP}, d AS (SELECT i, count(*) c FROM cop GROUP BY 1) SELECT i id, row_number() OVER (ORDER BY c, i) - 1 AS at FROM d",
    "gemv": "SELECT c_nationkey::BIGINT i, sum(s_nationkey % 5 + 1)::BIGINT v FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey WHERE s_nationkey % 2 = 0 GROUP BY 1",
    "mxv_push_salted": MXV + " GROUP BY 1",
    "mxv_row_split": MXV + " GROUP BY 1",
    "mxv_nonzero_split": MXV + " GROUP BY 1",
    "mxv_merge_path": MXV + " GROUP BY 1",
    "colouring_conflicts": "SELECT 0::BIGINT clashes, 0::BIGINT bare, 0::BIGINT repeated",
    "bfs_dense": "SELECT * FROM (VALUES (5::BIGINT, 1::BIGINT), (0, 2), (2, 2), (3, 2), (4, 3), (7, 3), (1, 4), (6, 4)) t(i, v)",
    "rgg_graph": """WITH a AS (SELECT c_custkey id, (((c_custkey * 2654435761 + 42) % 2147483648) * 1103515245 + 12345) % 2147483648 a FROM customer),
p AS (SELECT id, id // 500 q, a // 65536 % 1000 x, ((a * 1103515245 + 12345) % 2147483648) // 65536 % 1000 y FROM a)
SELECT u.id i, w.id j, 1::BIGINT v FROM p u JOIN p w ON u.q = w.q AND u.id <> w.id AND (u.x - w.x) * (u.x - w.x) + (u.y - w.y) * (u.y - w.y) <= 6400""",
    "mxv_pull": MXV + " GROUP BY 1",
    "mxv_push": MXV + " GROUP BY 1",
    "mxv_via_mxm": MXV + " GROUP BY 1",
    "mxv_pull_masked": MXV + " WHERE cop.i IN (SELECT i FROM m) GROUP BY 1",
    "mxv_push_masked": MXV + " WHERE cop.i IN (SELECT i FROM m) GROUP BY 1",
    "mxv_push_maskmerge": MXV + " WHERE cop.i IN (SELECT i FROM m) GROUP BY 1",
    "mxv_complement": MXV + " WHERE cop.i NOT IN (SELECT i FROM m) GROUP BY 1",
    "mxv_accum": f"WITH {COP}, {VEC}, {MASK}, y AS (SELECT cop.i, sum(cop.v * x.v)::BIGINT v FROM cop JOIN x ON x.i = cop.j WHERE cop.i IN (SELECT i FROM m) GROUP BY 1), o AS (SELECT p_partkey i, p_partkey % 5 + 1 v FROM part WHERE p_partkey % 2 = 0) SELECT i, sum(v)::BIGINT v FROM (SELECT * FROM y UNION ALL SELECT * FROM o) GROUP BY 1",
    "vxm": f"WITH {CUSTPART} SELECT j i, sum(v * (i % 3))::BIGINT v FROM cp GROUP BY 1",
    "pull_early_exit": f"WITH {COP} SELECT DISTINCT i FROM cop WHERE j % 40 = 0",
    "spmm": SPMM,
    "spmm_row_split": SPMM,
    "spmm_nonzero_split": SPMM,
    "mxm": f"WITH {COP2} SELECT a.i, b.j, sum(a.v * b.v)::BIGINT v FROM cop2 a JOIN cop2 b ON b.i = a.j GROUP BY 1, 2",
    "mxm_then_mask": MASKED_PAIR,
    "mxm_mask_first": MASKED_PAIR,
    "mxm_row_dot": MASKED_PAIR,
    "projection": f"WITH {USERKEY} SELECT a.i, b.i j, count(*)::BIGINT v FROM uk a JOIN uk b ON a.j = b.j AND a.i <> b.i GROUP BY 1, 2",
    "semiring_plus_times": semiring("sum", "cop.v * x.v").replace("sum(cop.v * x.v)", "sum(cop.v * x.v)::BIGINT"),
    "semiring_or_and": semiring("bool_or", "cop.v <> 0 AND x.v <> 0"),
    "semiring_min_plus": semiring("min", "cop.v + x.v"),
    "semiring_max_plus": semiring("max", "cop.v + x.v"),
    "semiring_min_times": semiring("min", "cop.v * x.v"),
    "semiring_min_second": semiring("min", "x.v"),
    "semiring_plus_pair": semiring("count", "x.v"),
    "semiring_user": semiring("max", "cop.v - x.v"),
    "monoid_plus": over("sum(v)::BIGINT"),
    "monoid_times": over("round(sum(log2(v)), 6)", "cop2"),
    "monoid_min": over("min(v)"),
    "monoid_max": over("max(v)"),
    "monoid_lor": over("bool_or(v >= 2)"),
    "monoid_land": over("bool_and(v >= 2)"),
    "monoid_lxor": over("count(*) FILTER (v >= 2) % 2 = 1"),
    "monoid_eq": over("count(*) FILTER (v < 2) % 2 = 0"),
    "bfs_parents": f"""WITH RECURSIVE {COP}, lv AS (SELECT 0::BIGINT i, 1::BIGINT v UNION SELECT e.j, lv.v + 1 FROM lv JOIN cop e ON e.i = lv.i WHERE lv.v < 6), d AS (SELECT i, min(v) v FROM lv GROUP BY 1)
SELECT e.j i, min(e.i) v FROM cop e JOIN d a ON a.i = e.i JOIN d b ON b.i = e.j AND b.v = a.v + 1 GROUP BY 1 UNION ALL SELECT 0, 0""",
    "bfs_multi": f"WITH RECURSIVE {COP}, lv AS (SELECT unnest([0, 1, 2])::BIGINT src, unnest([0, 1, 2])::BIGINT i, 1::BIGINT v UNION SELECT src, e.j, lv.v + 1 FROM lv JOIN cop e ON e.i = lv.i WHERE lv.v < 6) SELECT src, i, min(v) v FROM lv GROUP BY 1, 2",
    "bfs_userchain": f"WITH {CHAIN}, u AS (SELECT event_id i, row_number() OVER (ORDER BY ts, event_id) v FROM events WHERE user_id = 8) SELECT i, v FROM u",
    "bfs_weblink": levels(WEB + ", h AS (SELECT href, row_number() OVER (ORDER BY href) + 999999 id FROM (SELECT DISTINCT href FROM web)), wg AS (SELECT page_id i, id j FROM web JOIN h USING (href) UNION ALL SELECT id, page_id FROM web JOIN h USING (href))", "wg", "0::BIGINT", 12),
    "bfs_rmat": levels(rmat(), "rmat", "0::BIGINT", 8),
    "bfs_geo": levels(GEO, "geo", "0::BIGINT", 6),
    "apsp_conversations": f"WITH {CONV}, v AS (SELECT i FROM conv UNION SELECT j FROM conv) SELECT s.i src, b.i i, b.i - s.i v FROM conv s JOIN v b ON s.i <= b.i AND s.i // 8 = b.i // 8",
    "topk_pagerank": pagerank(10, "SELECT i, round(v, 9) v FROM p{k} ORDER BY round(v, 9) DESC, i LIMIT 10"),
    "cc_dupline": reach(LINES + ", h AS (SELECT line, row_number() OVER (ORDER BY line) + 999999999 id FROM (SELECT DISTINCT line FROM dl)), dg AS (SELECT doc_id i, id j FROM dl JOIN h USING (line) UNION ALL SELECT id, doc_id FROM dl JOIN h USING (line))", "dg", "WHERE i < 1000000000"),
    "cc_sizes": f"WITH c AS ({CC_CHAIN}) SELECT v, count(*)::BIGINT n FROM c GROUP BY 1",
    "cc_label_propagation": reach(GEO, "geo"),
    "cc_multistep": reach(GEO, "geo"),
    "tc_per_vertex": f"WITH {COP}, {PER} SELECT i, t::BIGINT v FROM t",
    "clustering_coeff": f"WITH {COP}, {PER}, d AS (SELECT i, count(*) d FROM cop GROUP BY 1) SELECT d.i, round(CASE WHEN d > 1 THEN 2.0 * coalesce(t, 0) / (d * (d - 1)) ELSE 0 END, 9)::DOUBLE v FROM d LEFT JOIN t ON t.i = d.i",
    "transitivity": f"WITH {COP}, c AS ({TRI.replace('WITH ' + COP + ', ', 'WITH ')}), d AS (SELECT i, count(*) d FROM cop GROUP BY 1) SELECT round(3.0 * (SELECT triangles FROM c) / sum(d * (d - 1) / 2), 9)::DOUBLE v FROM d",
    "touch_counts": f"WITH {COP}, {VEC}, {MASK} SELECT 'dense' kernel, count(*) * count(*) touches FROM part UNION ALL SELECT 'pull', count(*) FROM cop UNION ALL SELECT 'push', count(*) FROM cop WHERE j IN (SELECT i FROM x) UNION ALL SELECT 'pull_masked', count(*) FROM cop WHERE i IN (SELECT i FROM m) UNION ALL SELECT 'push_masked', count(*) FROM cop WHERE j IN (SELECT i FROM x)",
    "spmspv_flops": f"WITH {COP} SELECT count(*)::BIGINT flops FROM cop WHERE j % 4 = 0",
    "mxm_flops": f"WITH {COP2} SELECT count(*)::BIGINT flops FROM cop2 a JOIN cop2 b ON a.j = b.i",
    "mxm_nnz_ratio": f"WITH {COP}, l AS (SELECT i, j FROM cop WHERE i > j) SELECT (SELECT count(*) FROM (SELECT DISTINCT a.i, b.i j FROM l a JOIN l b ON a.j = b.j))::BIGINT unmasked, (SELECT count(*) FROM l)::BIGINT mask",
    "degree_stats": f"WITH {COP}, d AS (SELECT i, count(*) v FROM cop GROUP BY 1) SELECT count(*)::BIGINT n, sum(v)::BIGINT nnz, max(v)::BIGINT most, round(avg(v), 6) mean, round(avg((v < 64)::INT), 6) under_64 FROM d",
    "degree_hist": f"WITH {COP}, d AS (SELECT i, count(*) v FROM cop GROUP BY 1) SELECT (v // 16 * 16)::BIGINT degree, count(*)::BIGINT n FROM d GROUP BY 1",
    "frontier_sizes": f"WITH b AS ({BFS}) SELECT v, count(*)::BIGINT n FROM b GROUP BY 1",
    "copurchase_edges": f"WITH {COP} SELECT i, j, v FROM cop",
    "custpart_edges": f"WITH {CUSTPART} SELECT * FROM cp",
    "supppart_edges": "SELECT l_suppkey i, l_partkey j, min(l_quantity)::BIGINT v FROM lineitem GROUP BY 1, 2",
    "weblink_edges": f"WITH {WEB} SELECT page_id, href FROM web",
    "doctoken_edges": r"SELECT DISTINCT doc_id, token FROM (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[^\p{L}]+')) AS token FROM documents) WHERE token <> ''",
    "dupline_edges": f"WITH {LINES} SELECT doc_id, line FROM dl",
    "userchain_edges": f"WITH {CHAIN} SELECT i, j, 1::BIGINT v FROM chain",
    "userkey_edges": f"WITH {USERKEY} SELECT * FROM uk",
    "convchain_edges": f"WITH {CONV} SELECT * FROM conv",
    "embnear_edges": "SELECT a.vec_id i, b.vec_id j, 1::BIGINT v FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id WHERE list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) >= 0.3",
    "geo_edges": f"WITH {GEO} SELECT * FROM geo",
    "contam_edges": "SELECT DISTINCT doc_id, item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)",
    "rmat_edges": f"WITH {order_rmat()} SELECT * FROM rmat",
    "grid_edges": "WITH c AS (SELECT p_partkey i FROM part), e AS (SELECT a.i, b.i j FROM c a JOIN c b ON b.i = a.i + 1 WHERE a.i % 20 < 19 UNION ALL SELECT a.i, b.i FROM c a JOIN c b ON b.i = a.i + 20) SELECT i, j, 1::BIGINT v FROM e UNION ALL SELECT j, i, 1 FROM e",
    "stream_window_degrees": "SELECT date_trunc('day', ts)::TIMESTAMP AS day, user_id, count(*)::BIGINT n FROM events GROUP BY 1, 2",
    "stream_distinct_edges": f"WITH {USERKEY} SELECT i user_id, j k FROM uk",
    "stream_static_join": "SELECT event_id, c_name FROM events JOIN customer ON user_id = c_custkey",
    "stream_cc": reach(USERKEY + ", ug AS (SELECT i, j + 1000000 j FROM uk UNION ALL SELECT j + 1000000, i FROM uk)", "ug"),
    "filter_orders": "SELECT o_orderkey, o_custkey, o_orderstatus FROM orders WHERE o_totalprice > 100000 AND o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_orderstatus IS NOT NULL",
    "join_nation": "SELECT r_name, n_name, count(*)::BIGINT customers FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2",
    "join_left_anti": "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)",
    "join_left_semi": "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 200000)",
    "join_full": "SELECT coalesce(c.k, s.k) k, customers, suppliers FROM (SELECT c_nationkey k, count(*)::BIGINT customers FROM customer GROUP BY 1) c FULL JOIN (SELECT s_nationkey k, count(*)::BIGINT suppliers FROM supplier GROUP BY 1) s ON c.k = s.k",
    "join_range": "SELECT range band, count(*)::BIGINT parts FROM part JOIN range(10) ON p_retailprice >= range * 200 AND p_retailprice < range * 200 + 200 GROUP BY 1",
    "asof_events": "SELECT e.event_id, p.event_id last_purchase FROM events e LEFT JOIN LATERAL (SELECT event_id FROM events q WHERE q.user_id = e.user_id AND q.event_type = 'purchase' AND (q.ts, q.event_id) <= (e.ts, e.event_id) ORDER BY q.ts DESC, q.event_id DESC LIMIT 1) p ON true",
    "interval_join": "SELECT a.event_id, b.event_id later FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR",
    "agg_pricing": "SELECT l_returnflag, l_linestatus, sum(l_quantity)::BIGINT quantity, round(sum(l_extendedprice * (1 - l_discount)), 2) revenue, count(*)::BIGINT n, count(DISTINCT l_orderkey)::BIGINT orders FROM lineitem WHERE l_shipdate <= TIMESTAMP '1998-09-02' GROUP BY 1, 2",
    "agg_extremes": "SELECT o_orderstatus, arg_max(o_orderkey, (o_totalprice, o_orderkey)) dearest, arg_min(o_orderkey, (o_totalprice, o_orderkey)) cheapest, bool_or(o_totalprice > 300000) some_large, bool_and(o_totalprice > 1000) all_paid FROM orders GROUP BY 1",
    "cube_orders": "SELECT o_orderstatus, o_orderpriority, count(*)::BIGINT n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)",
    "rollup_customers": "SELECT c_mktsegment, c_nationkey, count(*)::BIGINT n FROM customer GROUP BY ROLLUP (c_mktsegment, c_nationkey)",
    "pivot_events": "SELECT user_id, nullif(count(*) FILTER (event_type = 'click'), 0)::BIGINT click, nullif(count(*) FILTER (event_type = 'purchase'), 0)::BIGINT purchase, nullif(count(*) FILTER (event_type = 'view'), 0)::BIGINT AS view FROM events GROUP BY 1",
    "running_sum": "SELECT o_orderkey, row_number() OVER w n, round(sum(o_totalprice) OVER (w ROWS UNBOUNDED PRECEDING), 2) so_far FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)",
    "ranks": "SELECT p_partkey, rank() OVER w AS rank, dense_rank() OVER w AS dense FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size DESC)",
    "topk_parts": "SELECT p_brand, place, p_partkey FROM (SELECT p_brand, p_partkey, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS place FROM part) WHERE place <= 3",
    "topk_orders": "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20",
    "edges_union": f"WITH {USERKEY} SELECT i, j FROM uk WHERE i % 2 = 0 OR j < 50",
    "edges_intersect": f"WITH {USERKEY} SELECT i, j FROM uk WHERE i % 2 = 0 AND j < 50",
    "edges_except": f"WITH {USERKEY} SELECT i, j FROM uk WHERE i % 2 = 0 AND j >= 50",
    "fn_strings": "SELECT p_partkey, upper(p_name) up, length(p_name) n, substring(p_brand, 1, 3) head, md5(p_type) digest FROM part",
    "fn_dates": "SELECT date_trunc('month', o_orderdate)::TIMESTAMP AS month, count(*)::BIGINT n FROM orders GROUP BY 1",
    "fn_json": "SELECT (props->>'$.k')::BIGINT k, count(*)::BIGINT n FROM events GROUP BY 1",
    "edge_list_roundtrip": f"WITH {USERKEY} SELECT * FROM uk",
    "scan_lineitem": "SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_quantity >= 45",
}
SQL |= {f"bfs_{n}": BFS for n in ("levels", "push", "pull", "pull_early_exit", "no_reuse", "no_mask", "via_mxm", "expand_contract", "several_hops", "edge_fraction", "two_thresholds", "unvisited_edges", "bytes_policy", "local_la")}
SQL |= {f"profile_{n}": BFS for n in ("cpu_la", "cpu_trav", "cpu_work", "gpu_front", "gpu_shard", "gpu_push", "gpu_lap")}
SQL |= {n: SSSP for n in ("sssp", "sssp_bf", "sssp_push")}
SQL["sssp_delta"] = SSSP_ALL
SQL |= {n: pagerank(10) for n in ("pagerank_k", "pagerank_push_k", "pagerank_shard_k")}
SQL |= {n: CC_CHAIN for n in ("cc", "cc_sparsified", "cc_full_jump", "cc_alternating", "cc_unconditional", "cc_edge_filter")}
SQL |= {n: TRI for n in ("tc", "tc_naive", "tc_multiply_first", "tc_row_dot", "tc_degree_ordered", "tc_fused", "tc_bitmap", "tc_binary_search")}
STEPS = "k AS (SELECT unnest(range(greatest(12, (SELECT ceil(log2(count(*)))::INT + 1 FROM part)))) step)"
SWEEP = f"{COP}, {STEPS}, sw AS (SELECT step, (SELECT count(*) FROM cop)::BIGINT pull, (SELECT count(*) FROM cop WHERE j < (1 << step::INT))::BIGINT push FROM k)"


def row_facts(name: str, edges: str) -> str:
    return f"SELECT '{name}' graph, count(DISTINCT i)::BIGINT AS rows, count(*)::BIGINT entries, CASE WHEN count(*) >= 9.35 * count(DISTINCT i) THEN 'row' ELSE 'nonzero' END strategy FROM {edges}"


def triangles_of(name: str, edges: str) -> str:
    return f"SELECT '{name}' graph, count(*)::BIGINT triangles FROM {edges} a JOIN {edges} b ON b.i = a.j AND a.i > a.j AND b.i > b.j JOIN {edges} c ON c.i = a.i AND c.j = b.j"


def low_product(name: str, edges: str) -> str:
    return f"SELECT '{name}' graph, (SELECT count(*) FROM (SELECT DISTINCT a.i, b.i k FROM {edges} a JOIN {edges} b ON a.j = b.j AND a.i > a.j AND b.i > b.j))::BIGINT unmasked, (SELECT count(*) FROM {edges} WHERE i > j)::BIGINT mask"


GRID = "gc AS (SELECT range i FROM range(400)), ge AS (SELECT i, i + 1 j FROM gc WHERE i % 20 < 19 UNION ALL SELECT i, i + 20 FROM gc WHERE i < 380), grid AS (SELECT i, j FROM ge UNION ALL SELECT j, i FROM ge)"
SQL |= {
    "input_sweep": f"WITH {SWEEP} SELECT step, pull, push FROM sw",
    "input_sweep_executed": f"WITH {COP}, {STEPS}, su AS (SELECT step, coalesce((SELECT sum(v) FROM cop WHERE j < (1 << step::INT)), 0)::BIGINT y FROM k) SELECT step, y pushed, y pulled FROM su",
    "mask_sweep": f"WITH {COP}, {STEPS} SELECT step, (SELECT count(*) FROM cop WHERE i < (1 << step::INT))::BIGINT pull_masked, (SELECT count(*) FROM cop WHERE j % 4 = 0)::BIGINT push_masked FROM k",
    "speedup_summary": f"WITH {SWEEP} SELECT round(exp(avg(ln(pull / push))), 6) geomean, round(max(pull / push), 6) peak FROM sw WHERE push > 0",
    "row_length_sweep": f"WITH {COP2}, {CUSTPART}, {CHAIN}, sp AS (SELECT DISTINCT l_suppkey i, l_partkey j FROM lineitem) " + " UNION ALL ".join(row_facts(*x) for x in (("supppart", "sp"), ("custpart", "cp"), ("copurchase2", "cop2"), ("userchain", "chain"))),
    "triangle_suite": f"WITH {COP2}, {rmat()}, {GRID} " + " UNION ALL ".join(triangles_of(*x) for x in (("copurchase", "cop"), ("copurchase2", "cop2"), ("rmat", "rmat"), ("grid", "grid"))),
    "component_suite": f"WITH {CONV} SELECT 'geo' graph, 5::BIGINT components UNION ALL SELECT 'grid', 1 UNION ALL SELECT 'convchain', count(DISTINCT i // 8) FROM conv UNION ALL SELECT 'userchain', count(*) FROM (SELECT user_id FROM events GROUP BY 1 HAVING count(*) > 1)",
    "weak_scaling_sizes": " UNION ALL ".join(f"SELECT * FROM (WITH {order_rmat(k, 1 << 10 - k)} SELECT {k}::BIGINT AS scale, count(DISTINCT i)::BIGINT vertices, count(*)::BIGINT edges FROM rmat)" for k in range(6, 11)),
    "sssp_parents": SSSP.replace("SELECT i, min(v) v FROM s GROUP BY i", "") + ", d AS (SELECT i, min(v) v FROM s GROUP BY i) SELECT w.j i, min(w.i) v FROM w JOIN d a ON a.i = w.i JOIN d b ON b.i = w.j AND b.v = a.v + w.v GROUP BY 1 UNION ALL SELECT 0, 0",
    "sql_bfs": f"WITH RECURSIVE {GEO}, lv(i, v) AS (SELECT 0::BIGINT, 1::BIGINT UNION ALL SELECT g.j, lv.v + 1 FROM lv JOIN g0 g ON g.i = lv.i) SELECT i, min(v) v FROM lv GROUP BY 1",
    "masked_product_suite": f"WITH {COP2}, {CHAIN} " + low_product("copurchase2", "cop2") + " UNION ALL " + low_product("userchain", "chain"),
}


def distances(name: str, edges: str, rounds: int) -> str:
    """Relaxing rounds from vertex 0 over weighted edges, written out: CTEs name_0 .. name_rounds."""
    w = f"{name}_w AS (SELECT i, j, (least(i, j) * 31 + greatest(i, j) * 17) % 64 + 1 v FROM {edges})"
    parts = [w, f"{name}_0 AS MATERIALIZED (SELECT 0::BIGINT i, 0::BIGINT v)"]
    for k in range(rounds):
        parts.append(f"{name}_{k + 1} AS MATERIALIZED (SELECT i, min(v) v FROM (SELECT i, v FROM {name}_{k} UNION ALL SELECT w.j, d.v + w.v FROM {name}_{k} d JOIN {name}_w w ON w.i = d.i) GROUP BY 1)")
    return ", ".join(parts)


def depths(name: str, edges: str, rounds: int) -> str:
    """Levels from vertex 0, written out."""
    parts = [f"{name}_0 AS MATERIALIZED (SELECT 0::BIGINT i, 1::BIGINT v)"]
    for k in range(rounds):
        parts.append(f"{name}_{k + 1} AS MATERIALIZED (SELECT i, min(v) v FROM (SELECT i, v FROM {name}_{k} UNION ALL SELECT e.j, {k + 2} FROM {name}_{k} d JOIN {edges} e ON e.i = d.i WHERE d.v = {k + 1}) GROUP BY 1)")
    return ", ".join(parts)


RGG = """a AS (SELECT range id, (((range * 2654435761 + 42) % 2147483648) * 1103515245 + 12345) % 2147483648 a FROM range(500)),
p AS (SELECT id, a // 65536 % 1000 x, ((a * 1103515245 + 12345) % 2147483648) // 65536 % 1000 y FROM a),
rgg AS (SELECT u.id i, w.id j, 1::BIGINT v FROM p u JOIN p w ON u.id <> w.id AND (u.x - w.x) * (u.x - w.x) + (u.y - w.y) * (u.y - w.y) <= 6400)"""
WORKED = "worked AS (SELECT split_part(e, '-', 1)::BIGINT i, split_part(e, '-', 2)::BIGINT j FROM (SELECT unnest(string_split('5-0 5-2 5-3 0-2 0-4 0-5 2-5 2-7 3-2 3-4 3-7 4-1 4-6 7-6 7-4 7-3 6-1 6-5 1-6 1-0', ' ')) e))"
WEBGRAPH = WEB + ", h AS (SELECT href, row_number() OVER (ORDER BY href) + 999999 id FROM (SELECT DISTINCT href FROM web)), wg AS (SELECT page_id i, id j FROM web JOIN h USING (href) UNION ALL SELECT id, page_id FROM web JOIN h USING (href))"
#: Graphs of the suites: edges as SQL, name of the edges, rounds that reach every vertex and settle every distance.
SUITE = {"rmat8": (rmat(8, 64), "rmat", 14), "rmat9": (rmat(9, 32), "rmat", 14), "rmat10": (rmat(10, 16), "rmat", 16), "rgg": (RGG, "rgg", 40), "geo": (GEO, "geo", 8)}
ALL_DEPTHS = SUITE | {"grid": (GRID, "grid", 40), "worked": (WORKED, "worked", 8)}


def facts(name: str, made: str, columns: str) -> str:
    edges, of, rounds = ALL_DEPTHS[name]
    maker = {"depths": depths, "distances": distances}[made]
    return f"SELECT * FROM (WITH {edges}, {maker('t', of, rounds)} SELECT '{name}' graph, {columns} FROM t_{rounds})"


REACHED = "count(*)::BIGINT reached, sum(v)::BIGINT total"
R8, R10 = rmat(8), rmat(10)
ANSWERS = f"""SELECT 'bfs' algorithm, x answer FROM (WITH {R8}, {depths("t", "rmat", 14)} SELECT sum(v)::DOUBLE x FROM t_14)
UNION ALL SELECT 'sssp', x FROM (WITH {R8}, {distances("t", "rmat", 14)} SELECT sum(v)::DOUBLE x FROM t_14)
UNION ALL SELECT 'pagerank', x FROM ({pagerank(5, "SELECT round(max(v), 6) x FROM p{k}", R8, "rmat", "SELECT DISTINCT i FROM rmat")})
UNION ALL SELECT 'cc', x FROM (SELECT sum(v)::DOUBLE x FROM ({reach(R8, "rmat")}))
UNION ALL SELECT 'tc', x FROM (WITH {R8} SELECT triangles::DOUBLE x FROM ({triangles_of("rmat", "rmat")}))"""


def _pairs(column: str, of: dict[str, str]) -> str:
    """Answers by algorithm, once for each name that an algorithm is listed under."""
    named = " UNION ALL ".join(f"SELECT '{a}' algorithm, '{n}' {column}" for a, names in of.items() for n in names.split(","))
    return f"SELECT {column}, algorithm, answer FROM ({named}) JOIN ({ANSWERS}) USING (algorithm)"


SQL |= {
    "bfs_suite": " UNION ALL ".join(facts(n, "depths", REACHED) for n in [*SUITE, "grid"]),
    "sssp_suite": " UNION ALL ".join(facts(n, "distances", REACHED) for n in SUITE),
    "product_suite": " UNION ALL ".join(facts(n, "depths", "sum(v)::BIGINT masked, sum(v)::BIGINT by_product") for n in [*SUITE, "worked"]),
    "pagerank_suite": " UNION ALL ".join(f"SELECT '{n}' graph, * FROM ({pagerank(5, 'SELECT round(max(v), 6) most, round(sum(v * v), 6) spread FROM p{k}', e, of, f'SELECT DISTINCT i FROM {of}')})" for n, (e, of, _) in SUITE.items()),
    "pagerank_weblink_k": pagerank(10, edges=WEBGRAPH, name="wg", vertices="SELECT DISTINCT i FROM wg"),
    "parallelism_suite": f"SELECT policy, parts, reached, total FROM (VALUES ('edge_fraction', 2::BIGINT), ('edge_fraction', 4), ('two_thresholds', 2), ('two_thresholds', 4)) t(policy, parts), ({facts('rmat10', 'depths', REACHED)})",
    "ablation_suite": _pairs("toggle", {"bfs": "all,no mask,no operand reuse,early exit,push only,pull only", "sssp": "all,no sparsification,push only,pull only", "pagerank": "all,windows", "cc": "all,no sparsification,full jump", "tc": "all,multiply first,degree order"}),
    "profile_suite": _pairs(
        "profile",
        {
            "bfs": "reference,cpu_la,cpu_trav,cpu_work,gpu_front,gpu_shard,gpu_push,gpu_lap",
            "sssp": "reference,cpu_la,cpu_trav,cpu_work,gpu_front,gpu_shard,gpu_push",
            "pagerank": "reference,cpu_la,cpu_trav,cpu_work,gpu_front,gpu_shard,gpu_push",
            "cc": "reference,cpu_trav,cpu_work,gpu_front",
            "tc": "reference,cpu_la,cpu_trav,cpu_work,gpu_front,gpu_lap",
        },
    ),
    "extract_vector": f"WITH {VEC} SELECT i // 2 i, v FROM x WHERE i % 2 = 0 AND i < 100",
    "extract_row": f"WITH {COP} SELECT j i, v FROM cop WHERE i = 3",
    "extract_column": f"WITH {CUSTPART} SELECT i, v FROM cp WHERE j = 3",
    "assign_list": "WITH p AS (SELECT p_partkey i FROM part) SELECT i, i % 5 + 1 v FROM p WHERE i % 3 = 0 AND NOT (i % 5 = 0 AND i < 100) UNION ALL SELECT i * 5, i % 5 + 1 FROM p WHERE i % 2 = 0 AND i * 5 < 100",
    "assign_sub": f"WITH {COP2} SELECT i, j, v FROM cop WHERE NOT (i % 2 = 0 AND i < 100 AND j % 3 = 0 AND j < 90) UNION ALL SELECT i * 2, j * 3, v FROM cop2 WHERE i * 2 < 100 AND j * 3 < 90",
    "kronecker": f"WITH {COP2}, {WORKED} SELECT a.i * 8 + b.i i, a.j * 8 + b.j j, a.v FROM cop2 a, worked b",
    "arg_rows": f"WITH {COP} SELECT i, arg_max(j, (v, -j)) v FROM cop GROUP BY 1",
    "arg_rows_least": f"WITH {COP} SELECT i, arg_min(j, (v, j)) v FROM cop GROUP BY 1",
    "mxm_dense_side": f"WITH {CUSTPART} SELECT i, k j, sum(v * ((j * (k + 3)) % 7))::BIGINT v FROM cp, (SELECT unnest(range(4)) k) GROUP BY 1, 2",
    "lazy_triangles": TRI,
    "lazy_mxv": f"WITH {COP}, {VEC}, {MASK} SELECT cop.i, (3 * sum(cop.v * x.v) + 1)::BIGINT v FROM cop JOIN x ON x.i = cop.j WHERE cop.i IN (SELECT i FROM m) GROUP BY 1",
    "udf_semiring": MXV + " GROUP BY 1",
    "udtf_neighbours": f"WITH {COP2} SELECT i, j FROM cop2",
    "binary_ops": "WITH q AS (SELECT p_partkey % 5 + 1 a, p_partkey % 3 b FROM part) "
    + " UNION ALL ".join(
        f"SELECT '{n}' op, round(sum(({e})::DOUBLE), 6) v FROM q"
        for n, e in {
            "first": "a",
            "second": "b",
            "pair": "1",
            "any": "a",
            "min": "least(a, b)",
            "max": "greatest(a, b)",
            "plus": "a + b",
            "minus": "a - b",
            "rminus": "b - a",
            "times": "a * b",
            "div": "CASE WHEN b <> 0 THEN a / b END",
            "rdiv": "b / a",
            "eq": "(a = b)::INT",
            "ne": "(a <> b)::INT",
            "gt": "(a > b)::INT",
            "lt": "(a < b)::INT",
            "ge": "(a >= b)::INT",
            "le": "(a <= b)::INT",
            "lor": "(a <> 0 OR b <> 0)::INT",
            "land": "(a <> 0 AND b <> 0)::INT",
            "lxor": "((a <> 0) <> (b <> 0))::INT",
            "lxnor": "((a <> 0) = (b <> 0))::INT",
        }.items()
    ),
    "typed_plus": " UNION ALL ".join(
        f"SELECT '{n}' AS domain, count(v)::BIGINT n, max(v)::DOUBLE most FROM (SELECT unnest([CASE WHEN a + b <= {top} THEN a + b END, CASE WHEN a - b >= {low} THEN a - b END]) v FROM (SELECT p_partkey a, p_partkey * 2 b FROM part) WHERE b <= {top})"
        for n, low, top in (
            ("int8", -128, 127),
            ("int16", -32768, 32767),
            ("int32", -2147483648, 2147483647),
            ("int64", -(2**62), 2**62),
            ("uint8", 0, 255),
            ("uint16", 0, 65535),
            ("uint32", 0, 4294967295),
            ("uint64", 0, 2**62),
            ("fp32", -(2**62), 2**62),
            ("fp64", -(2**62), 2**62),
        )
    ),
}
SQL["mxm_directed"] = SQL["mxm_dense_side"]

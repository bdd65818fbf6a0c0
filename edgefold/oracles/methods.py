"""SQL twins of the method queries. A violation count's twin is the number it must be: 0."""

from __future__ import annotations

from ..graph.ids import mix_sql
from .graphs import ctes, distances, greedy, labels, measures, placed, predecessors, ranks, reach, relaxed

K = 8
ZERO = "SELECT 0::BIGINT AS n"
RANKS = ranks("handoff", 10)
MIXED = f"({mix_sql('src')} * 31 + {mix_sql('dst')}) % 1000003, src, dst"


def _cut(k: int) -> str:
    return f"SELECT {k} AS k, sum((({mix_sql('src')} % {k}) <> ({mix_sql('dst')} % {k}))::INT)::BIGINT AS cut, round(avg((({mix_sql('src')} % {k}) <> ({mix_sql('dst')} % {k}))::INT), 6) AS rate FROM e"


def _union(texts: list[str]) -> str:
    return " UNION ALL ".join(f"SELECT * FROM ({t})" for t in texts)


def _rule(rule: str) -> str:
    one = lambda g: f"WITH {placed(g, K, rule)} SELECT '{g}' AS graph, {K} AS k, (SELECT count(*) FROM x) AS proxies, (SELECT count(*) FROM q JOIN h a ON a.id = src JOIN h b ON b.id = dst WHERE a.home <> b.home) AS cut"
    return _union([one(g) for g in ("purchase", "purchase_rev")])


def _gain() -> str:
    one = lambda g, rule: f"WITH {placed(g, K, rule)} SELECT '{g}' AS graph, '{rule}' AS rule, round((SELECT count(*) FROM q JOIN h a ON a.id = src JOIN h b ON b.id = dst WHERE a.home <> b.home) / (SELECT count(*) FROM x), 6) AS gain"
    return _union([one(g, r) for g in ("purchase", "purchase_rev") for r in ("at_source", "at_target")])


def _skew() -> str:
    one = lambda g: f"WITH {placed(g, K)} SELECT '{g}' AS graph, role, count(*) AS n, round(100 * count(*) / (SELECT count(*) FROM x), 4) AS pct FROM x GROUP BY role"
    return _union([one(g) for g in ("purchase", "purchase_rev", "hyperlink")])


LOCAL = """l AS MATERIALIZED (SELECT pid, (row_number() OVER (PARTITION BY pid ORDER BY o, id) - 1)::INT AS lid, id, role FROM (
  SELECT home AS pid, id, 'home' AS role, 0 AS o FROM h UNION ALL SELECT pid, id, role, CASE role WHEN 'in' THEN 1 ELSE 2 END FROM x))"""


def _profile() -> str:
    one = lambda g: f"""WITH {ctes(g)}, d AS (SELECT id, count(*) AS d FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e) GROUP BY id),
      s AS (SELECT d, count(*) AS n FROM d GROUP BY d),
      r AS (SELECT d, n, coalesce(sum(n) OVER (ORDER BY d DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS first FROM s)
      SELECT '{g}' AS graph, ((first * 10) // (SELECT sum(n) FROM s))::BIGINT AS bucket, sum(n)::BIGINT AS n, round(sum(n * d) / (SELECT sum(n * d) FROM s), 4) AS edge_share FROM r GROUP BY 2"""  # noqa: E731
    return _union([one(g) for g in ("sharedline", "purchase")])


BETWEEN = f"""WITH RECURSIVE {ctes('handoff_strong')},
b AS MATERIALIZED (SELECT DISTINCT src, dst FROM e WHERE src <> dst),
lv(s, id, d) USING KEY (s, id) AS (SELECT id, id, 0 FROM v UNION
  SELECT DISTINCT lv.s, b.dst, lv.d + 1 FROM lv JOIN b ON b.src = lv.id LEFT JOIN recurring.lv r ON r.s = lv.s AND r.id = b.dst WHERE r.id IS NULL),
sg(s, id, d, n) AS (SELECT s, id, 0, 1.0::DOUBLE FROM lv WHERE d = 0 UNION ALL
  SELECT sg.s, b.dst, sg.d + 1, sum(sg.n) FROM sg JOIN b ON b.src = sg.id JOIN lv ON lv.s = sg.s AND lv.id = b.dst AND lv.d = sg.d + 1 GROUP BY sg.s, b.dst, sg.d + 1),
mx AS (SELECT max(d) AS m FROM lv),
dl(s, id, d, x) AS (SELECT s, id, d, 0.0::DOUBLE FROM sg, mx WHERE d = m UNION ALL
  SELECT p.s, p.id, p.d, coalesce(c.x, 0.0) FROM sg p JOIN (SELECT DISTINCT d FROM dl) t ON p.d = t.d - 1 LEFT JOIN (
    SELECT p.s, p.id, sum(p.n / w.n * (1 + dl.x)) AS x FROM dl JOIN sg w ON w.s = dl.s AND w.id = dl.id JOIN b ON b.dst = dl.id JOIN sg p ON p.s = dl.s AND p.id = b.src AND p.d = dl.d - 1 GROUP BY p.s, p.id) c ON c.s = p.s AND c.id = p.id)
SELECT v.id, round(coalesce(sum(x) FILTER (s <> dl.id), 0.0), 4) AS score FROM v LEFT JOIN dl ON dl.id = v.id GROUP BY v.id"""

TRACE = f"""WITH RECURSIVE {ctes('thread')},
n AS (SELECT id // 1000 AS c, count(*) AS len FROM v GROUP BY 1),
t(step, frontier) AS (SELECT 0::BIGINT, (SELECT count(*) FROM v)::BIGINT UNION ALL SELECT step + 1, (SELECT sum(greatest(len - step - 1, 0)) FROM n)::BIGINT FROM t WHERE frontier > 0)
SELECT step, frontier FROM t WHERE frontier > 0"""

OBLIVIOUS = f"""WITH RECURSIVE {ctes('trade')},
""" + ",\n".join(
    greedy(f"(SELECT * FROM e WHERE ({mix_sql('dst')} * 17 + {mix_sql('src')}) % 1000003 % 2 = {i})", MIXED, 4).replace("o AS MATERIALIZED", f"o{i} AS MATERIALIZED").replace("JOIN o ON", f"JOIN o{i} o ON").replace("g(edge_seq", f"g{i}(edge_seq").replace("FROM g s", f"FROM g{i} s")
    for i in (0, 1)
) + "\n" + " UNION ALL ".join(f"SELECT edge_seq, src, dst, {i} AS loader, pid FROM g{i} WHERE edge_seq >= 0" for i in (0, 1))


def _greedy(order: str, directed: bool = True) -> str:
    return f"WITH RECURSIVE {ctes('trade')},\n{greedy('e', order, 4, directed)}\nSELECT edge_seq, src, dst, pid FROM g WHERE edge_seq >= 0"


WIRE = f"""WITH {placed('purchase', 4)}, pe AS (SELECT CASE role WHEN 'out' THEN home ELSE pid END AS f, CASE role WHEN 'out' THEN pid ELSE home END AS t, role, count(*) AS n FROM x JOIN h ON h.id = x.id GROUP BY 1, 2, 3)
SELECT count(*) AS pairs, sum(n)::BIGINT AS messages, sum(ceil(n / 63))::BIGINT AS buffers, sum(ceil(n / 63) * 8 + n * 16)::BIGINT AS bytes FROM pe"""
TOPOLOGY = f"""WITH {placed('purchase', 4)}, c AS (SELECT (SELECT count(*) FROM v) + (SELECT count(*) FROM x) AS n, (SELECT count(*) FROM q) AS e)
SELECT n AS local_ids, e AS edges, 8 * n + 4 * e AS bytes, 2 * (8 * n + 4 * e) + 8 * e AS gas_bytes FROM c"""

AXES = f"""WITH {placed('handoff', K)}, c AS (SELECT (SELECT count(*) FROM q) AS e, (SELECT count(DISTINCT dst) FROM q) AS t, (SELECT count(*) FROM v) AS n, (SELECT count(*) FROM x) AS p, (SELECT count(*) FROM (SELECT DISTINCT pid, id FROM x)) AS m)
SELECT 'one-sided flat' AS engine, 'edges by source' AS data_model, 'one-sided messages' AS computation_model, 'merged messages' AS communication_model, t AS rows_moved FROM c
UNION ALL SELECT 'one-sided proxied', 'proxy graph', 'one-sided messages', 'one direction per proxy', p FROM c
UNION ALL SELECT 'gather-apply-scatter', 'edges with state', 'split phases', 'shared edge values', e FROM c
UNION ALL SELECT 'mirror', 'vertex-cut with mirrors', 'split phases', 'collect and broadcast', 2 * m FROM c
UNION ALL SELECT 'message super-steps', 'edges by source', 'vertex programs', 'stored messages', e FROM c
UNION ALL SELECT 'map/reduce rounds', 'adjacency records', 'map and reduce', 'whole graph each round', e + n FROM c
UNION ALL SELECT 'matrix products', 'sparse matrix', 'semiring products', 'vector shuffles', n FROM c
UNION ALL SELECT 'rdd', 'partitioned pairs', 'joins and reductions', 'merged pairs', t FROM c"""

ORACLES: dict[str, str] = {
    **{f"pagerank_{n}scaled_10": RANKS for n in ("", "gas_", "bsp_", "bsp_merged_", "mirror_", "proxied_", "nopremerge_", "two_level_", "spmv_", "mapreduce_", "rdd_")},
    "pagerank_double_5": ranks("handoff", 5, scaled=False, value="rank"),
    "pagerank_dangling": ranks("hyperlink", 5),
    "pagerank_fanin": ranks("purchase", 5),
    "pagerank_message_woken": ranks("hyperlink", 5, wake_all=False),
    "checkpoint_resume_equal": RANKS,
    **{n: distances("handoff", 0) for n in ("sssp_dist", "sssp_proxied", "sssp_gas", "sssp_bsp")},
    "sssp_weighted_pred": predecessors("handoff_weighted", 0),
    "sssp_unreached": distances("thread", 0),
    "bfs_levels": distances("handoff_strong", 0, "level", unit=True),
    "path_to_vertex": relaxed(
        "handoff_weighted",
        "SELECT 0::BIGINT, 0::BIGINT",
        "d.x + b.w",
        """, f AS MATERIALIZED (SELECT v.id, (SELECT min(b.src) FROM b JOIN d p ON p.id = b.src WHERE b.dst = v.id AND p.x + b.w = d.x) AS pred FROM v JOIN d ON d.id = v.id),
t(step, id, pred) AS (SELECT 0::BIGINT, id, pred FROM f WHERE id = 7 UNION ALL SELECT step + 1, f.id, f.pred FROM t JOIN f ON f.id = t.pred) SELECT step, id FROM t""",
    ),
    **{f"cc_{g}": labels(g) for g in ("sharedline", "thread", "hyperlink", "purchase")},
    "cc_rmat8": labels("rmat8"),
    "cc_sizes": labels("sharedline", "SELECT x::BIGINT AS label, count(*) AS n FROM d GROUP BY 1"),
    "cc_contract": labels("thread"),
    "cc_proxied": labels("sharedline"),
    "cc_gas": labels("sharedline"),
    "rmat_scale8_degrees": f"WITH {ctes('rmat8_events')} SELECT src AS id, count(*) AS out_degree FROM e GROUP BY src",
    "convergence_trace": TRACE,
    "scc_strong": reach("handoff_strong") + " SELECT x.a AS id, min(x.b)::BIGINT AS scc FROM p x JOIN p y ON x.a = y.b AND x.b = y.a GROUP BY x.a",
    "betweenness_strong_all": BETWEEN,
    "place_hash_edge_cut": f"WITH {ctes('purchase')} " + " UNION ALL ".join(_cut(k) for k in (4, 8, 16)),
    **{f"proxy_measures_k{k}": " UNION ALL ".join(measures(g, k) for g in ("handoff", "purchase")) for k in (4, 8, 16)},
    "place_at_source": _rule("at_source"),
    "place_at_target": _rule("at_target"),
    "proxy_gain": _gain(),
    "proxy_skew": _skew(),
    "edge_balance": f"WITH {placed('handoff', K)} SELECT pid, count(*) AS edges FROM q GROUP BY pid",
    "proxy_rows": f"WITH {placed('trade', 4)} SELECT home AS pid, id, 'home' AS role FROM h UNION ALL SELECT pid, id, role FROM x",
    "routing_lists": f"WITH {placed('trade', 4)} SELECT id, string_agg(pid::VARCHAR, ',' ORDER BY pid) AS parts FROM x WHERE role = 'out' GROUP BY id",
    "local_ids": f"WITH {placed('trade', 4)}, {LOCAL} SELECT pid, lid, id, role FROM l",
    "csr_rows": f"""WITH {placed('trade', 4)}, {LOCAL}, r AS (SELECT q.pid, a.lid, count(*) AS degree, string_agg(b.lid::VARCHAR, ',' ORDER BY b.lid) AS targets FROM q
  JOIN l a ON a.pid = q.pid AND a.id = q.src AND a.role IN ('home', 'out') JOIN l b ON b.pid = q.pid AND b.id = q.dst AND b.role IN ('home', 'in') GROUP BY 1, 2)
SELECT pid, lid, coalesce(sum(degree) OVER (PARTITION BY pid ORDER BY lid ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS "offset", degree, targets FROM r""",
    "objective_rows": f"WITH {placed('purchase', K)}, m AS (SELECT max(n) AS max_load, sum(n) AS e FROM (SELECT count(*) AS n FROM q GROUP BY pid)) SELECT round((SELECT count(*) FROM x) / {K}, 4) AS avg_proxies, max_load, max_load < 1.1 * e / {K} AS feasible FROM m",
    "ghost_counts": f"WITH {placed('handoff', K)}, a AS (SELECT src, dst, s.home AS hs, t.home AS hd FROM e JOIN h s ON s.id = src JOIN h t ON t.id = dst WHERE s.home <> t.home) SELECT count(*) AS ghosts FROM (SELECT hs, dst FROM a UNION SELECT hd, src FROM a)",
    "greedy_assign_trade": _greedy("src, dst"),
    "greedy_assign_trade_mixed": _greedy(MIXED),
    "greedy_mirror_assign_trade": _greedy(MIXED, directed=False),
    "greedy_oblivious_trade": OBLIVIOUS,
    "greedy_coordinated_trade": _greedy(MIXED),
    "greedy_two_pass_parts": _greedy("(SELECT count(*) FROM e x WHERE x.src = e.src) + (SELECT count(*) FROM e x WHERE x.dst = e.dst) DESC, src, dst"),
    "engine_axes": AXES,
    "greedy_two_pass_loads": f"WITH {ctes('trade')} SELECT count(*) AS edges FROM e",
    "message_counts": f"""WITH {placed('purchase', 4)}, m AS (SELECT q.pid, dst, home, count(*) AS n FROM q JOIN h ON h.id = dst GROUP BY 1, 2, 3)
SELECT sum(n)::BIGINT AS emitted, coalesce(sum(n) FILTER (pid = home), 0)::BIGINT AS local_msgs, (SELECT count(*) FROM x WHERE role = 'out') AS s_msgs, count(*) FILTER (pid <> home) AS c_msgs FROM m""",
    "gas_touch_counts": f"WITH {ctes('handoff')} SELECT 6 * count(*) AS touches, 3 * count(*) AS stored_rows FROM e",
    "wire_bytes": WIRE,
    "topology_bytes": TOPOLOGY,
    "fold_collisions": f"WITH {ctes('handoff')} SELECT count(*) AS messages, count(DISTINCT dst) AS targets FROM e",
    "degree_profile": _profile(),
    "sql_reachability": reach("handoff_strong") + " SELECT b AS id FROM p WHERE a = 0",
    "cosine_knn16": "SELECT src, dst FROM (SELECT a.vec_id AS src, b.vec_id AS dst, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 9) DESC, b.vec_id) AS k FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) WHERE k <= 16",
    "knn_degrees": "SELECT 16 AS out_degree, count(*) AS n FROM embeddings",
    **{n: ZERO for n in ("sssp_triangle_violations", "bipartite_matching_violations", "matching_maximal_violations", "colouring_violations", "weighted_matching_violations", "min_proxy_violations", "proxy_bound_violations", "proxy_direction_violations", "greedy_guarded_balance_violations", "edgecut_violations")},
}

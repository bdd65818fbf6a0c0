"""Graphs as CTEs: ``e`` (src, dst, w) and ``v`` (id), from the given tables."""

from __future__ import annotations

from ..graph.ids import KINDS, mix_sql
from ..graph.rmat import rmat_sql

ENDS = "v AS MATERIALIZED (SELECT src AS id FROM e UNION SELECT dst FROM e)"
LINES = f"""sl AS (SELECT DISTINCT doc_id, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) > 20),
sp AS (SELECT DISTINCT doc_id * 16 + {KINDS['document']} AS src, ('0x' || substr(md5(line), 1, 14))::BIGINT * 16 + {KINDS['line']} AS dst FROM sl)"""

HANDOFF = """ev AS (SELECT user_id::BIGINT AS u, (lead(user_id) OVER (ORDER BY ts, event_id))::BIGINT AS nx FROM events),
{0} AS MATERIALIZED (SELECT u AS src, nx AS dst, count(*) AS w FROM ev WHERE nx IS NOT NULL AND u <> nx GROUP BY u, nx)"""
PURCHASE = """{0} AS MATERIALIZED (SELECT o_custkey * 16 AS src, l_suppkey * 16 + 1 AS dst, count(*) AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2)"""

EDGES = {
    "handoff": HANDOFF.format("e"),
    "handoff_strong": HANDOFF.format("h") + ",\ne AS MATERIALIZED (SELECT * FROM h WHERE w >= 3)",
    "handoff_weighted": HANDOFF.format("h") + ",\ne AS MATERIALIZED (SELECT src, dst, 1 + ((src * 7919 + dst * 104729) % 1000003) % 100 AS w FROM h)",
    "purchase": PURCHASE.format("e"),
    "purchase_rev": PURCHASE.format("p") + ",\ne AS MATERIALIZED (SELECT dst AS src, src AS dst, w FROM p)",
    "trade": PURCHASE.format("p") + """,
e AS MATERIALIZED (SELECT c_nationkey::BIGINT AS src, s_nationkey::BIGINT AS dst, sum(w)::BIGINT AS w FROM p JOIN customer ON c_custkey = src // 16 JOIN supplier ON s_suppkey = dst // 16
  WHERE c_nationkey <> s_nationkey GROUP BY 1, 2)""",
    "hyperlink": f"""hl AS (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) AS path FROM pages),
e AS MATERIALIZED (SELECT DISTINCT page_id * 16 + {KINDS['page']} AS src, ('0x' || substr(md5(path), 1, 14))::BIGINT * 16 + {KINDS['path']} AS dst FROM hl)""",
    "sharedline": LINES + ",\ne AS MATERIALIZED (SELECT src, dst FROM sp WHERE dst IN (SELECT dst FROM sp GROUP BY dst HAVING count(*) >= 2))",
    "thread": """th AS (SELECT conv_id * 1000 + turn AS id, conv_id * 1000 + lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS nx FROM conversations),
e AS MATERIALIZED (SELECT id AS src, nx AS dst, 1::BIGINT AS w FROM th WHERE nx IS NOT NULL)""",
    "part_supplier": "e AS MATERIALIZED (SELECT DISTINCT l_partkey * 16 + 2 AS src, l_suppkey * 16 + 1 AS dst FROM lineitem)",
    "rmat8_events": f"e AS MATERIALIZED ({rmat_sql(8, numbers='(SELECT event_id AS i FROM events)')})",
    "rmat8": f"e AS MATERIALIZED ({rmat_sql(8)})",
}


def ctes(graph: str) -> str:
    """CTE text of ``e`` and ``v``."""
    if graph == "thread":
        return EDGES[graph] + ",\nv AS MATERIALIZED (SELECT DISTINCT id FROM th)"
    if graph == "rmat8":
        return EDGES[graph] + ",\nv AS MATERIALIZED (SELECT i AS id FROM range(256) t(i))"
    return EDGES[graph] + ",\n" + ENDS


def ranks(graph: str, steps: int, scaled: bool = True, wake_all: bool = True, value: str = "rank_e9") -> str:
    """PageRank unrolled, one CTE per step."""
    first, share = ("1000000000::BIGINT", "(r.x // g.d)") if scaled else ("1.0::DOUBLE", "(r.x / g.d)")
    new = "150000000 + (85 * {0}) // 100" if scaled else "0.15::DOUBLE + 0.85::DOUBLE * {0}"
    zero = "0" if scaled else "0.0"
    settled = new.format(f"coalesce(a.s, {zero})") if wake_all else f"CASE WHEN a.s IS NULL THEN r.x ELSE {new.format('a.s')} END"
    parts = [ctes(graph), "g AS MATERIALIZED (SELECT src, count(*) AS d FROM e GROUP BY src)", f"r0 AS MATERIALIZED (SELECT id, {first} AS x FROM v)"]
    for i in range(steps):
        kind = "::BIGINT" if scaled else ""
        parts.append(f"a{i} AS MATERIALIZED (SELECT e.dst AS id, sum{'' if scaled else ''}({share}){kind} AS s FROM e JOIN g ON g.src = e.src JOIN r{i} r ON r.id = e.src GROUP BY e.dst)")
        parts.append(f"r{i + 1} AS MATERIALIZED (SELECT r.id, {settled} AS x FROM r{i} r LEFT JOIN a{i} a ON a.id = r.id)")
    out = f"x::BIGINT AS {value}" if scaled else f"round(x, 6) AS {value}"
    return "WITH " + ",\n".join(parts) + f"\nSELECT id, {out} FROM r{steps}"


def relaxed(graph: str, start: str, step: str, select: str, undirected: bool = False) -> str:
    """Shortest values by keyed recursion: ``start`` rows (id, x), ``step`` an expression over d.x and b.w."""
    both = "b AS MATERIALIZED (SELECT src, dst, w FROM e)" if not undirected else "b AS MATERIALIZED (SELECT src, dst, 0 AS w FROM e UNION SELECT dst, src, 0 FROM e)"
    return f"""WITH RECURSIVE {ctes(graph)},
{both},
d(id, x) USING KEY (id) AS (
  {start}
  UNION
  SELECT c.id, min(c.x) FROM (SELECT b.dst AS id, {step} AS x FROM d JOIN b ON b.src = d.id) c LEFT JOIN recurring.d r ON r.id = c.id WHERE r.x IS NULL OR c.x < r.x GROUP BY c.id)
{select}"""


def distances(graph: str, source: int, column: str = "dist", unit: bool = False) -> str:
    return relaxed(graph, f"SELECT {source}::BIGINT, 0::BIGINT", "d.x + " + ("1" if unit else "b.w"), f"SELECT v.id, d.x::BIGINT AS {column} FROM v LEFT JOIN d ON d.id = v.id")


def predecessors(graph: str, source: int) -> str:
    select = """SELECT v.id, d.x::BIGINT AS dist, (SELECT min(b.src) FROM b JOIN d p ON p.id = b.src WHERE b.dst = v.id AND p.x + b.w = d.x)::BIGINT AS pred FROM v LEFT JOIN d ON d.id = v.id"""
    return relaxed(graph, f"SELECT {source}::BIGINT, 0::BIGINT", "d.x + b.w", select)


def labels(graph: str, select: str = "SELECT id, x::BIGINT AS label FROM d") -> str:
    return relaxed(graph, "SELECT id, id FROM v", "d.x", select, undirected=True)


def reach(graph: str) -> str:
    """CTEs with ``p`` (a, b): b is reachable from a, itself included."""
    return f"""WITH RECURSIVE {ctes(graph)},
p(a, b) AS (SELECT id, id FROM v UNION SELECT p.a, e.dst FROM p JOIN e ON e.src = p.b)"""


def placed(graph: str, k: int, rule: str = "edge") -> str:
    """CTEs with ``q`` (src, dst, pid) and ``h`` (id, home) under arithmetic placements."""
    home = f"h AS MATERIALIZED (SELECT id, ({mix_sql('id')} % {k})::INT AS home FROM v)"
    part = {
        "edge": f"SELECT src, dst, (({mix_sql('src')} * 31 + {mix_sql('dst')}) % 1000003 % {k})::INT AS pid FROM e",
        "at_source": "SELECT src, dst, home AS pid FROM e JOIN h ON h.id = src",
        "at_target": "SELECT src, dst, home AS pid FROM e JOIN h ON h.id = dst",
    }[rule]
    proxies = """x AS MATERIALIZED (SELECT DISTINCT q.pid, q.src AS id, 'out' AS role FROM q JOIN h ON h.id = q.src WHERE q.pid <> h.home
  UNION ALL SELECT DISTINCT q.pid, q.dst, 'in' FROM q JOIN h ON h.id = q.dst WHERE q.pid <> h.home)"""
    return f"{ctes(graph)},\n{home},\nq AS MATERIALIZED ({part}),\n{proxies}"


def measures(graph: str, k: int) -> str:
    return f"""SELECT '{graph}' AS graph, {k} AS k, * FROM (WITH {placed(graph, k)}
SELECT (SELECT count(*) FROM v) AS v, (SELECT count(*) FROM q) AS e, (SELECT count(*) FROM x WHERE role = 'out') AS s, (SELECT count(*) FROM x WHERE role = 'in') AS c,
  (SELECT count(*) FROM v) + (SELECT count(*) FROM (SELECT DISTINCT pid, id FROM x)) AS replicas, (SELECT max(n) FROM (SELECT count(*) AS n FROM q GROUP BY pid)) AS max_load,
  (SELECT count(*) FROM q JOIN h a ON a.id = src JOIN h b ON b.id = dst WHERE a.home <> b.home) AS cut)"""


def greedy(graph_edges: str, order: str, k: int, directed: bool = True, n_vertices: int = 25) -> str:
    """Keyless recursion that places one edge per step; vertices are 0..n_vertices - 1 and edges are numbered by ``order``."""
    seen_u, seen_v = ("outs", "ins") if directed else ("outs", "outs")
    score = f"((s.{seen_u}[o.src + 1] >> i) & 1) + ((s.{seen_v}[o.dst + 1] >> i) & 1) + (list_max(s.loads) - s.loads[i + 1]) / (1.0 + list_max(s.loads) - list_min(s.loads))"
    scores = f"list_transform(range({k}), lambda i: ({score})::DOUBLE)"
    mark = lambda name, ends: f"list_transform({name}, lambda x, i: CASE WHEN {' OR '.join(f'i = {e} + 1' for e in ends)} THEN x | (1 << pid) ELSE x END)"
    outs = mark("outs", ["src"] if directed else ["src", "dst"])
    ins = mark("ins", ["dst"])
    zeros = f"list_transform(range({n_vertices}), lambda x: 0)"
    return f"""o AS MATERIALIZED (SELECT row_number() OVER (ORDER BY {order}) - 1 AS edge_seq, src, dst FROM {graph_edges}),
g(edge_seq, src, dst, pid, outs, ins, loads) AS (
  SELECT -1::BIGINT, 0::BIGINT, 0::BIGINT, -1, {zeros}, {zeros}, list_transform(range({k}), lambda x: 0)
  UNION ALL
  SELECT edge_seq, src, dst, pid, {outs}, {ins}, list_transform(loads, lambda x, i: CASE WHEN i = pid + 1 THEN x + 1 ELSE x END)
  FROM (SELECT edge_seq, src, dst, outs, ins, loads, (list_position(sc, list_max(sc)) - 1)::INT AS pid FROM (
    SELECT o.edge_seq, o.src, o.dst, s.outs, s.ins, s.loads, {scores} AS sc FROM g s JOIN o ON o.edge_seq = s.edge_seq + 1)))"""

"""SQL for the same results, to be run by another engine on the same tables.

Iterative rankings are recursive queries that carry the stop test with them.
"""

from __future__ import annotations

from ..config import RankConfig

TEMPORAL = {
    "part_flow": """SELECT src, dst, ts FROM (SELECT l_partkey AS src, lead(l_partkey) OVER w AS dst, lead(o_orderdate) OVER w AS ts
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey
  WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey, l_linenumber, l_partkey)) WHERE dst IS NOT NULL""",
    "cust_supp": "SELECT o_custkey AS src, l_suppkey + 1000000000 AS dst, o_orderdate AS ts FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "user_relay": """SELECT src, dst, ts FROM (SELECT user_id AS src, lead(user_id) OVER w AS dst, lead(ts) OVER w AS ts
  FROM events WINDOW w AS (ORDER BY ts, event_id)) WHERE dst IS NOT NULL""",
    "state_flow": """SELECT src, dst, ts FROM (SELECT state AS src, lead(state) OVER w AS dst, lead(ts) OVER w AS ts
  FROM (SELECT user_id, ts, event_id, event_type || ':' || json_extract_string(props, '$.k') AS state FROM events)
  WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) WHERE dst IS NOT NULL""",
}
STATIC = {
    "site_links": """SELECT url AS src, unnest(regexp_extract_all(html, 'href="([^"#]+)', 1)) AS dst FROM pages""",
    "order_road": """SELECT a AS src, b AS dst FROM road UNION ALL SELECT b, a FROM road""",
    "part_supp_sym": """SELECT l_partkey AS src, l_suppkey + 1000000000 AS dst FROM lineitem UNION ALL SELECT l_suppkey + 1000000000, l_partkey FROM lineitem""",
}
ROAD = """road AS (SELECT * FROM (
  SELECT o_orderkey AS a, lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS b FROM orders
  UNION ALL
  SELECT o_orderkey, lead(o_orderkey) OVER (PARTITION BY c_nationkey ORDER BY o_orderdate, o_orderkey) FROM orders JOIN customer ON o_custkey = c_custkey) WHERE b IS NOT NULL)"""


def graph_ctes(graph: str) -> str:
    """raw, plain (distinct, no loops), verts, edges (with loops), deg, num."""
    body = TEMPORAL.get(graph) or STATIC[graph]
    lead = ROAD + ",\n" if graph == "order_road" else ""
    return f"""{lead}raw AS ({body}),
plain AS (SELECT DISTINCT src, dst FROM raw WHERE src IS NOT NULL AND dst IS NOT NULL AND src <> dst),
verts AS (SELECT src AS v FROM raw UNION SELECT dst FROM raw),
edges AS (SELECT src, dst FROM plain UNION ALL SELECT v, v FROM verts),
deg AS (SELECT src AS v, count(*) AS out_deg FROM edges GROUP BY src),
num AS (SELECT count(*) AS n FROM verts)"""


def batch_ctes(fraction: float, seed: int = 42) -> str:
    """delta (op, src, dst), new_edges, new_deg over the CTEs of a graph."""
    return f"""size AS (SELECT greatest(1, CAST(round_even({fraction} * (SELECT count(*) FROM edges), 0) AS BIGINT)) AS b),
parts AS (SELECT b, CAST(round_even(0.2 * b, 0) AS BIGINT) AS n_del, b - CAST(round_even(0.2 * b, 0) AS BIGINT) AS n_ins FROM size),
gone AS (SELECT src, dst FROM (SELECT src, dst, row_number() OVER (ORDER BY md5('{seed}|' || src || '|' || dst), src, dst) AS k FROM plain), parts WHERE k <= n_del),
named AS (SELECT v, row_number() OVER (ORDER BY v) - 1 AS k FROM verts),
drawn AS (SELECT id, CAST('0x' || substr(md5('{seed}|s|' || id), 1, 8) AS BIGINT) % n AS a, CAST('0x' || substr(md5('{seed}|t|' || id), 1, 8) AS BIGINT) % n AS b
  FROM (SELECT unnest(range(0, 4 * n_ins + 16)) AS id FROM parts), num),
fresh AS (SELECT src, dst FROM (SELECT x.v AS src, y.v AS dst, min(id) AS id FROM drawn JOIN named x ON x.k = drawn.a JOIN named y ON y.k = drawn.b
    WHERE x.v <> y.v AND NOT EXISTS (SELECT 1 FROM plain p WHERE p.src = x.v AND p.dst = y.v) GROUP BY x.v, y.v
    ORDER BY min(id) LIMIT (SELECT n_ins FROM parts))),
delta AS (SELECT 'ins' AS op, src, dst FROM fresh UNION ALL SELECT 'del', src, dst FROM gone),
new_edges AS (SELECT src, dst FROM edges WHERE NOT EXISTS (SELECT 1 FROM gone g WHERE g.src = edges.src AND g.dst = edges.dst) UNION ALL SELECT src, dst FROM fresh),
new_deg AS (SELECT src AS v, count(*) AS out_deg FROM new_edges GROUP BY src)"""


def power_ctes(name: str, start: str, cfg: RankConfig, edges: str = "edges", deg: str = "deg", active: str = "") -> str:
    """A recursive ranking: name (i, v, r, d, visits).  ``start`` selects (v, r)."""
    hold = f"EXISTS (SELECT 1 FROM {active} f WHERE f.v = o.v)" if active else "true"
    return f"""{name}(i, v, r, d, visits) AS (
  SELECT 0, v, CAST(r AS DOUBLE), CAST('inf' AS DOUBLE), CAST(0 AS BIGINT) FROM ({start})
  UNION ALL
  SELECT o.i + 1, o.v, CASE WHEN {hold} THEN x.nr ELSE o.r END,
         max(CASE WHEN {hold} THEN abs(x.nr - o.r) ELSE 0 END) OVER (), CASE WHEN {hold} THEN x.c ELSE 0 END
  FROM {name} o JOIN (
    SELECT e.dst AS v, (1 - {cfg.alpha}) / (SELECT n FROM num) + {cfg.alpha} * sum(s.r / g.out_deg) AS nr, count(*) AS c
    FROM {name} s JOIN {edges} e ON e.src = s.v JOIN {deg} g ON g.v = s.v GROUP BY e.dst) x ON x.v = o.v
  WHERE o.d > {cfg.tol} AND o.i < {cfg.max_iter})"""


def last(name: str) -> str:
    return f"SELECT v, round(r, 9) AS rank_r, CAST(i AS BIGINT) AS iterations FROM {name} WHERE i = (SELECT max(i) FROM {name})"


SEEDS = """seeds AS (SELECT dst AS v FROM delta WHERE op = 'del' UNION SELECT e.dst FROM new_edges e JOIN delta q ON q.src = e.src)"""
REACH = """reach(v) AS (SELECT v FROM seeds UNION SELECT e.dst FROM reach JOIN new_edges e ON e.src = reach.v)"""


def frontier_ctes(name: str, prev: str, cfg: RankConfig, prune: bool) -> str:
    """A recursive ranking with an expanding frontier: name (i, v, r, flag, ever, d, visits)."""
    a, n = cfg.alpha, "(SELECT n FROM num)"
    new = f"({a} * (t.s - o.r / g.out_deg) + (1 - {a}) / {n}) / (1 - {a} / g.out_deg)" if prune else f"(1 - {a}) / {n} + {a} * t.s"
    keep = f"u.flag AND abs(u.nr - u.r) / greatest(u.nr, u.r) > {cfg.tol_prune}" if prune else "u.flag"
    upd = f"""SELECT o.i, o.v, o.r, o.flag, o.ever, t.c, {new} AS nr FROM {name} o
    JOIN (SELECT e.dst AS v, sum(s.r / g.out_deg) AS s, count(*) AS c FROM {name} s JOIN new_edges e ON e.src = s.v JOIN new_deg g ON g.v = s.v GROUP BY e.dst) t ON t.v = o.v
    JOIN new_deg g ON g.v = o.v WHERE o.d > {cfg.tol} AND o.i < {cfg.max_iter}"""
    return f"""{name}(i, v, r, flag, ever, d, visits) AS (
  SELECT 0, p.v, p.r, s.v IS NOT NULL, s.v IS NOT NULL, CAST('inf' AS DOUBLE), CAST(0 AS BIGINT) FROM ({prev}) p LEFT JOIN seeds s ON s.v = p.v
  UNION ALL
  SELECT u.i + 1, u.v, CASE WHEN u.flag THEN u.nr ELSE u.r END, ({keep}) OR h.v IS NOT NULL, u.ever OR h.v IS NOT NULL,
         max(CASE WHEN u.flag THEN abs(u.nr - u.r) ELSE 0 END) OVER (), CASE WHEN u.flag THEN u.c ELSE 0 END
  FROM ({upd}) u LEFT JOIN (SELECT DISTINCT e.dst AS v FROM ({upd}) q JOIN new_edges e ON e.src = q.v
    WHERE q.flag AND abs(q.nr - q.r) / greatest(q.nr, q.r) > {cfg.tol_frontier}) h ON h.v = u.v)"""


UNIFORM = "SELECT v, 1.0 / (SELECT n FROM num) AS r FROM verts"
OLD = "SELECT v, r FROM old WHERE i = (SELECT max(i) FROM old)"

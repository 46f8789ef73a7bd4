"""The derived graphs and chained or recursive analyses in DuckDB SQL."""

from __future__ import annotations

G1 = """g1 AS (SELECT o_custkey AS src, nxt AS dst, o_totalprice AS weight, o_orderdate AS created, o_orderpriority AS etype, o_orderstatus AS st
  FROM (SELECT *, lead(o_custkey) OVER (PARTITION BY o_orderdate ORDER BY o_orderkey) AS nxt FROM orders) WHERE nxt IS NOT NULL AND nxt <> o_custkey)"""
G1D = G1 + ", g1d AS (SELECT DISTINCT src, dst FROM g1), g1v AS (SELECT c_custkey AS id FROM customer)"
G2 = """g2l AS (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem),
g2 AS MATERIALIZED (SELECT DISTINCT a.l_partkey AS src, b.l_partkey AS dst FROM g2l a JOIN g2l b USING (l_orderkey) WHERE a.l_partkey <> b.l_partkey),
g2v AS (SELECT p_partkey AS id FROM part)"""
G3 = """g3 AS (SELECT user_id AS src, nxt AS dst, value AS weight, ts AS created, event_type AS etype FROM
  (SELECT *, lead(user_id) OVER (PARTITION BY date_trunc('hour', ts) ORDER BY ts, event_id) AS nxt FROM events) WHERE nxt IS NOT NULL AND nxt <> user_id),
g3v AS (SELECT src AS id FROM g3 UNION SELECT dst FROM g3)"""
G5 = """g5 AS (SELECT DISTINCT 'p:' || page_id AS src, 'u:' || href AS dst FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages))"""
G4 = """g4 AS (SELECT DISTINCT o_custkey AS src, l_suppkey + 1000000000 AS dst FROM orders JOIN lineitem ON l_orderkey = o_orderkey)"""
G7 = """g7 AS (SELECT conv_id * 1000 + turn AS src, conv_id * 1000 + nxt AS dst FROM (SELECT *, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt FROM conversations) WHERE nxt IS NOT NULL),
g7v AS (SELECT conv_id * 1000 + turn AS id FROM conversations)"""
W9 = G1 + """, w9v AS (SELECT c_custkey AS id FROM customer WHERE c_mktsegment IN ('BUILDING', 'MACHINERY', 'HOUSEHOLD')),
w9 AS (SELECT src, dst FROM g1 WHERE etype IN ('1-URGENT', '2-HIGH') AND src IN (SELECT id FROM w9v) AND dst IN (SELECT id FROM w9v))"""


def pagerank(edges: str, vertices: str, rounds: int, sources: str = "standard", prefix: str = "r", weight: str = "1", start: str | None = None) -> str:
    """Chained CTEs ``{prefix}0 .. {prefix}{rounds}`` of (id, rank); ``weight`` is an expression on an edge, ``start`` the one id to restart at."""
    n = f"(SELECT count(*) FROM {vertices})"
    base = f"CASE WHEN v.id = {start} THEN 1.0::DOUBLE ELSE 0.0 END" if start else f"1.0::DOUBLE / {n}"
    out = [f"{prefix}deg AS MATERIALIZED (SELECT src AS id, sum({weight}) AS d FROM {edges} GROUP BY src)", f"{prefix}0 AS MATERIALIZED (SELECT v.id, {base} AS rank FROM {vertices} v)"]
    for k in range(1, rounds + 1):
        last = f"{prefix}{k - 1}"
        sums = f"SELECT e.dst AS id, sum(r.rank / d.d * {weight}) AS s FROM {edges} e JOIN {last} r ON r.id = e.src JOIN {prefix}deg d ON d.id = e.src GROUP BY e.dst"
        if sources == "literal":
            body = f"SELECT s.id, 0.15 * {base} + 0.85 * s.s AS rank FROM ({sums}) s JOIN {vertices} v ON v.id = s.id"
        else:
            loose = f" + (SELECT coalesce(sum(rank), 0) FROM {last} WHERE id NOT IN (SELECT id FROM {prefix}deg)) * {base}" if sources == "redistribute" else ""
            body = f"SELECT v.id, 0.15 * {base} + 0.85 * (coalesce(s.s, 0){loose}) AS rank FROM {vertices} v LEFT JOIN ({sums}) s ON s.id = v.id"
        out.append(f"{prefix}{k} AS MATERIALIZED ({body})")
    return ", ".join(out)


def first_settled(rounds: int, tol: float, prefix: str = "r") -> str:
    """The ranks of the first of ``rounds`` rounds in which none moved by more than ``tol``, as CTE ``settled``."""
    moved = " UNION ALL ".join(f"SELECT {k} AS k, max(abs(a.rank - b.rank)) AS m FROM {prefix}{k} a JOIN {prefix}{k - 1} b USING (id)" for k in range(1, rounds + 1))
    every = " UNION ALL ".join(f"SELECT {k} AS k, id, rank FROM {prefix}{k}" for k in range(1, rounds + 1))
    return f"moved AS ({moved}), settled AS (SELECT id, rank FROM ({every}) WHERE k = (SELECT coalesce(min(k) FILTER (WHERE m <= {tol}), {rounds}) FROM moved))"


def bfs(edges: str, source: str, name: str = "d", depth: int = 200) -> str:
    """CTEs that end in ``{name}(id, dist)`` of reached vertices."""
    return f"""{name}w(id, dist) AS (SELECT {source}, 0::BIGINT UNION SELECT e.dst, w.dist + 1 FROM {name}w w JOIN {edges} e ON e.src = w.id WHERE w.dist < {depth}),
{name} AS (SELECT id, min(dist) AS dist FROM {name}w GROUP BY id)"""


def levels(edges: str, source: str, name: str = "d") -> str:
    """Hop distances by a keyed recursion that visits each vertex once."""
    return f"""{name}(id, dist) USING KEY (id) AS (SELECT {source} AS id, 0::BIGINT AS dist UNION
  SELECT e.dst, min(w.dist + 1) FROM {name} w JOIN {edges} e ON e.src = w.id LEFT JOIN recurring.{name} p ON p.id = e.dst WHERE p.dist IS NULL OR w.dist + 1 < p.dist GROUP BY e.dst)"""


def labels(edges: str, vertices: str, name: str = "c") -> str:
    """Smallest label along ``edges`` by a keyed recursion."""
    return f"""{name}(id, component) USING KEY (id) AS (SELECT id, id AS component FROM {vertices} UNION
  SELECT e.dst, min(w.component) FROM {name} w JOIN {edges} e ON e.src = w.id JOIN recurring.{name} p ON p.id = e.dst WHERE w.component < p.component GROUP BY e.dst)"""


def both_ways(edges: str, name: str) -> str:
    return f"{name} AS MATERIALIZED (SELECT src, dst FROM {edges} UNION SELECT dst, src FROM {edges})"


#: Pairs with common neighbours, from the list of sources of each target: every later source of a list meets every earlier one.
PAIRS = """lists AS (SELECT dst, list_sort(list(src)) AS near FROM {e} GROUP BY dst),
firsts AS (SELECT near, unnest(near) AS n1, unnest(range(1, len(near) + 1)) AS i FROM lists),
pairs AS (SELECT n1, n2, count(*) AS common FROM (SELECT n1, unnest(near[i + 1:]) AS n2 FROM firsts) WHERE n1 <> n2 GROUP BY n1, n2)"""
OVERLAP = ", " + PAIRS + " SELECT n1, n2, common FROM pairs WHERE common > {t}"
#: For each vertex its wedges less those that an edge from their end back to their start closes; ``{h}`` halves them on undirected graphs.
TIES = """, ins AS (SELECT dst AS id, count(*) AS i FROM {e} GROUP BY dst), outs AS (SELECT src AS id, count(*) AS o FROM {e} GROUP BY src),
back AS (SELECT a.src AS id, count(*) AS n FROM {e} a JOIN {e} b ON b.src = a.dst AND b.dst = a.src GROUP BY a.src),
closed AS (SELECT a.dst AS id, count(*) AS n FROM {e} a JOIN {e} c ON c.dst = a.src JOIN {e} b ON b.src = a.dst AND b.dst = c.src WHERE a.src <> b.dst GROUP BY a.dst),
open AS (SELECT id, i * o - coalesce(back.n, 0) - coalesce(closed.n, 0) AS n FROM ins JOIN outs USING (id) LEFT JOIN back USING (id) LEFT JOIN closed USING (id))
SELECT id, (n // {h})::BIGINT AS pairs FROM open WHERE n // {h} > {t}"""
TRIANGLES = "SELECT a.src AS a, a.dst AS b, b.dst AS c FROM {e} a JOIN {e} b ON b.src = a.dst JOIN {e} c ON c.src = a.src AND c.dst = b.dst WHERE a.src < a.dst AND b.src < b.dst"

"""The SQL that registered queries are held against: common table expressions over the given tables, in DuckDB's dialect."""

from __future__ import annotations

KEY_BITS = 56


def node(code: int, column: str) -> str:
    return f"(({code}::BIGINT << {KEY_BITS}) | {column}::BIGINT)"


NODES = f"""
nodes0 AS (
  SELECT {node(1, "r_regionkey")} AS node_id, 'region:' || r_regionkey AS node_key, 'region' AS rel, r_name AS text FROM region
  UNION ALL SELECT {node(2, "n_nationkey")}, 'nation:' || n_nationkey, 'nation', n_name FROM nation
  UNION ALL SELECT {node(3, "c_custkey")}, 'customer:' || c_custkey, 'customer', concat_ws(' ', c_name, c_mktsegment) FROM customer
  UNION ALL SELECT {node(4, "s_suppkey")}, 'supplier:' || s_suppkey, 'supplier', s_name FROM supplier
  UNION ALL SELECT {node(5, "p_partkey")}, 'part:' || p_partkey, 'part', concat_ws(' ', p_name, p_brand, p_type) FROM part
  UNION ALL SELECT {node(6, "o_orderkey")}, 'orders:' || o_orderkey, 'orders', concat_ws(' ', o_orderstatus, o_orderpriority) FROM orders),
refs AS (
  SELECT {node(2, "n_nationkey")} AS src, {node(1, "n_regionkey")} AS dst, 'nation>region' AS etype FROM nation
  UNION ALL SELECT {node(3, "c_custkey")}, {node(2, "c_nationkey")}, 'customer>nation' FROM customer
  UNION ALL SELECT {node(4, "s_suppkey")}, {node(2, "s_nationkey")}, 'supplier>nation' FROM supplier
  UNION ALL SELECT {node(6, "o_orderkey")}, {node(3, "o_custkey")}, 'orders>customer' FROM orders
  UNION ALL SELECT DISTINCT {node(6, "l_orderkey")}, {node(5, "l_partkey")}, 'orders>part' FROM lineitem
  UNION ALL SELECT DISTINCT {node(6, "l_orderkey")}, {node(4, "l_suppkey")}, 'orders>supplier' FROM lineitem),
ins AS (SELECT dst AS node_id, count(*) AS indeg FROM refs GROUP BY dst),
outs AS (SELECT src AS node_id, count(*) AS outdeg FROM refs GROUP BY src),
nodes AS (
  SELECT n.*, coalesce(indeg, 0)::BIGINT AS indeg, coalesce(outdeg, 0)::BIGINT AS outdeg, coalesce(indeg, 0)::DOUBLE AS prestige
  FROM nodes0 n LEFT JOIN ins USING (node_id) LEFT JOIN outs USING (node_id)),
edges AS (
  SELECT src, dst, etype, 'fwd' AS direction, 1.0::DOUBLE AS weight FROM refs
  UNION ALL SELECT dst, src, etype, 'back', log2(1.0 + indeg) FROM refs JOIN ins ON refs.dst = ins.node_id)"""

FIELDS = [("region", "r_regionkey", 1, ("r_name",)), ("nation", "n_nationkey", 2, ("n_name",)), ("customer", "c_custkey", 3, ("c_name", "c_mktsegment")), ("supplier", "s_suppkey", 4, ("s_name",)), ("part", "p_partkey", 5, ("p_name", "p_brand", "p_type")), ("orders", "o_orderkey", 6, ("o_orderstatus", "o_orderpriority"))]
POSTINGS = "postings AS (SELECT term, node_id, node_key, rel, field, count(*)::BIGINT AS tf FROM (" + " UNION ALL ".join(f"SELECT unnest(regexp_extract_all(lower({f}), '[a-z0-9]+')) AS term, {node(code, key)} AS node_id, '{rel}:' || {key} AS node_key, '{rel}' AS rel, '{f}' AS field FROM {rel}" for rel, key, code, fields in FIELDS for f in fields) + ") GROUP BY ALL)"


def queries(sets: dict[str, tuple[str, ...]]) -> str:
    rows = ", ".join(f"('{q}', '{t}')" for q, terms in sorted(sets.items()) for t in dict.fromkeys(terms))
    return f"queries(query_id, term) AS (VALUES {rows}),\nmatches AS (SELECT DISTINCT query_id, term, node_id, node_key FROM postings JOIN queries USING (term)),\ncomplete AS (SELECT query_id FROM (SELECT query_id, count(DISTINCT term) AS n FROM queries GROUP BY 1) JOIN (SELECT query_id, count(DISTINCT term) AS n FROM matches GROUP BY 1) USING (query_id, n))"


def distances(max_cost: float, unit: bool = False, allowed: str = "TRUE", slack: float = 1e-9) -> str:
    """dist(query_id, term, node_id, dist) by a keyed recursion: relax until nothing improves."""
    weight = "1.0" if unit else "min(weight)"
    return f"""
links AS (SELECT src, dst, {weight} AS w FROM edges WHERE {allowed} GROUP BY src, dst),
walk(query_id, term, node_id, dist) USING KEY (query_id, term, node_id) AS (
  SELECT query_id, term, node_id, 0.0::DOUBLE FROM matches WHERE query_id IN (SELECT query_id FROM complete)
  UNION
  SELECT f.query_id, f.term, l.src, min(f.dist + l.w)
  FROM walk f JOIN links l ON l.dst = f.node_id
  LEFT JOIN recurring.walk r ON r.query_id = f.query_id AND r.term = f.term AND r.node_id = l.src
  WHERE f.dist + l.w <= {max_cost + slack} AND (r.dist IS NULL OR f.dist + l.w < r.dist - {slack})
  GROUP BY f.query_id, f.term, l.src),
dist AS (SELECT * FROM walk)"""


def answers(pool: int, hops: int = 12, slack: float = 1e-9) -> str:
    """scored(query_id, root, ..., node_score, edge_score): the cheapest roots, their least ways, and the parts of the score."""
    return f"""
sums AS (SELECT query_id, node_id AS root, round(sum(dist), 6) AS cost FROM dist JOIN (SELECT query_id, count(DISTINCT term) AS need FROM queries GROUP BY 1) USING (query_id) GROUP BY query_id, node_id, need HAVING count(*) = need),
roots AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY cost, root) AS r FROM sums) WHERE r <= {pool}),
hop AS (
  SELECT d.query_id, d.term, d.node_id, min(l.dst) AS next_id
  FROM dist d JOIN links l ON l.src = d.node_id JOIN dist a ON a.query_id = d.query_id AND a.term = d.term AND a.node_id = l.dst
  WHERE abs(l.w + a.dist - d.dist) <= {slack} GROUP BY ALL),
way(query_id, root, term, src, dst, step) AS (
  SELECT r.query_id, r.root, d.term, r.root, h.next_id, 1 FROM roots r JOIN dist d ON d.query_id = r.query_id AND d.node_id = r.root LEFT JOIN hop h ON h.query_id = d.query_id AND h.term = d.term AND h.node_id = d.node_id
  UNION ALL
  SELECT w.query_id, w.root, w.term, w.dst, h.next_id, step + 1 FROM way w LEFT JOIN hop h ON h.query_id = w.query_id AND h.term = w.term AND h.node_id = w.dst WHERE w.dst IS NOT NULL AND step < {hops}),
branch AS (SELECT DISTINCT query_id, root, src, dst FROM way WHERE dst IS NOT NULL),
trees AS (SELECT query_id, root, count(*) AS n_edges, sum(w) AS total, count(*) FILTER (WHERE src = root) AS branches FROM branch JOIN links USING (src, dst) GROUP BY 1, 2),
members AS (SELECT query_id, root, src AS node_id FROM branch UNION SELECT query_id, root, dst FROM branch UNION SELECT query_id, root, root FROM roots),
ends AS (SELECT DISTINCT query_id, root, src AS node_id FROM way WHERE dst IS NULL),
leaves AS (SELECT query_id, root, string_agg(node_key, ',' ORDER BY node_key) AS leaf_keys, sum(prestige) AS leaf_weight, bool_or(node_id = root) AS root_holds FROM ends JOIN nodes USING (node_id) GROUP BY 1, 2),
scored AS (
  SELECT l.query_id, l.root, n.node_key AS root_key, leaf_keys, root_holds, coalesce(n_edges, 0)::BIGINT AS n_edges, (SELECT count(*) FROM members m WHERE m.query_id = l.query_id AND m.root = l.root)::BIGINT AS n_nodes,
    coalesce(branches, 0) AS branches, coalesce(total, 0.0) AS total, CASE WHEN n_edges IS NULL THEN n.prestige ELSE n.prestige + leaf_weight END AS node_score, 1 / (1 + coalesce(total, 0.0)) AS edge_score
  FROM leaves l JOIN nodes n ON n.node_id = l.root LEFT JOIN trees t ON t.query_id = l.query_id AND t.root = l.root)"""

"""Statements for an independent engine: the derived graphs, bounded recursion with list columns, and outputs."""

from __future__ import annotations

from ..sources.catalog import EDGE_KINDS, NODE_KINDS

BIT = 1 << 48


def n(kind: str, key: str) -> str:
    return f"({NODE_KINDS[kind] * BIT} + CAST({key} AS BIGINT))"


def e(kind: str, key: str) -> str:
    return f"({EDGE_KINDS[kind] * BIT} + CAST({key} AS BIGINT))"


def pair(kind: str, a: str, b: str) -> str:
    return e(kind, f"CAST({a} AS BIGINT) * {1 << 24} + {b}")


def named(kind: str, text: str) -> str:
    return n(kind, f"('0x' || substr(md5({text}), 1, 11))::BIGINT")


TRADE = f"""tp AS (
  SELECT s_nationkey AS a, c_nationkey AS b, sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS cents
  FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
  WHERE s_nationkey <> c_nationkey GROUP BY ALL),
trade AS (SELECT {pair('TRADES_WITH', 'a', 'b')} AS eid, {n('Nation', 'a')} AS src, {n('Nation', 'b')} AS dst
  FROM (SELECT *, row_number() OVER (PARTITION BY a ORDER BY cents DESC, b) AS r FROM tp) WHERE r <= 2)"""

RELAY = f"""rl AS (SELECT event_type, user_id AS a, lead(user_id) OVER w AS b, lead(event_type) OVER w AS bt FROM events
  WINDOW w AS (PARTITION BY CAST(ts AS DATE) ORDER BY ts, event_id)),
relay AS (SELECT DISTINCT {pair('HANDS_TO', 'a', 'b')} AS eid, {n('User', 'a')} AS src, {n('User', 'b')} AS dst FROM rl WHERE event_type = 'purchase' AND bt = 'purchase')"""

SOCIAL = f"""oc AS (SELECT * FROM orders JOIN customer ON o_custkey = c_custkey),
kn AS (SELECT o_custkey AS a, lead(o_custkey) OVER w AS b FROM oc WHERE o_orderstatus = 'F' WINDOW w AS (PARTITION BY c_mktsegment, o_orderpriority ORDER BY o_orderdate, o_orderkey)),
knows AS (SELECT DISTINCT {pair('KNOWS', 'a', 'b')} AS eid, {n('Person', 'a')} AS src, {n('Person', 'b')} AS dst FROM kn WHERE b IS NOT NULL AND a <> b),
lk AS (SELECT o_custkey AS a, o_orderkey AS o, lead(o_orderkey) OVER w AS b FROM oc WHERE o_orderstatus = 'P' WINDOW w AS (PARTITION BY c_mktsegment, o_orderpriority ORDER BY o_orderdate, o_orderkey)),
likes AS (SELECT {e('LIKES', 'o')} AS eid, {n('Person', 'a')} AS src, {n('Message', 'b')} AS dst FROM lk WHERE b IS NOT NULL),
created AS (SELECT {e('HAS_CREATOR', 'o_orderkey')} AS eid, {n('Message', 'o_orderkey')} AS src, {n('Person', 'o_custkey')} AS dst FROM orders)"""

LOGISTICS = f"""placed AS (SELECT {e('PLACED_BY', 'o_orderkey')} AS eid, {n('Message', 'o_orderkey')} AS src, {n('Person', 'o_custkey')} AS dst FROM orders),
contains_ AS (SELECT {pair('CONTAINS', 'l_orderkey', 'l_partkey')} AS eid, {n('Message', 'l_orderkey')} AS src, {n('Part', 'l_partkey')} AS dst, sum(l_quantity) AS quantity FROM lineitem GROUP BY l_orderkey, l_partkey),
supplies AS (SELECT DISTINCT {pair('SUPPLIES', 'l_suppkey', 'l_partkey')} AS eid, {n('Supplier', 'l_suppkey')} AS src, {n('Part', 'l_partkey')} AS dst FROM lineitem),
lives AS (SELECT {e('LIVES_IN', 'c_custkey')} AS eid, {n('Person', 'c_custkey')} AS src, {n('Nation', 'c_nationkey')} AS dst FROM customer),
based AS (SELECT {e('BASED_IN', 's_suppkey')} AS eid, {n('Supplier', 's_suppkey')} AS src, {n('Nation', 's_nationkey')} AS dst FROM supplier),
partof AS (SELECT {e('PART_OF', 'n_nationkey')} AS eid, {n('Nation', 'n_nationkey')} AS src, {n('Region', 'n_regionkey')} AS dst FROM nation)"""

CLICKS = f"""cl AS (SELECT *, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS b FROM events),
clicks AS (SELECT {e('NEXT', 'event_id')} AS eid, {n('Event', 'event_id')} AS src, {n('Event', 'b')} AS dst, CAST(json_extract_string(props, '$.k') AS VARCHAR) AS k FROM cl WHERE b IS NOT NULL)"""

DIALOGUE = f"""dl AS (SELECT conv_id * 1024 + turn AS a, lead(conv_id * 1024 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS b FROM conversations),
dialogue AS (SELECT {e('REPLIED_BY', 'a')} AS eid, {n('Turn', 'a')} AS src, {n('Turn', 'b')} AS dst FROM dl WHERE b IS NOT NULL)"""

COPIES = f"""cp AS (SELECT doc_id, lead(doc_id) OVER (PARTITION BY text ORDER BY doc_id) AS b FROM documents),
copies AS (SELECT {e('COPY_OF', 'doc_id')} AS eid, {n('Document', 'doc_id')} AS src, {n('Document', 'b')} AS dst FROM cp WHERE b IS NOT NULL)"""

_MODES = {
    "walk": ("true", "true"),
    "trail": ("true", "NOT list_contains(p.edges, e.eid)"),
    "acyclic": ("src <> dst", "NOT list_contains(p.nodes, e.dst)"),
    "simple": ("true", "p.src <> p.dst AND NOT list_contains(p.nodes[2:], e.dst)"),
}


def recursion(name: str, base: str, mode: str, bound: int, seed: str = "true") -> str:
    """A recursive table of paths over single edges of `base`."""
    if mode == "shortest":
        return f"""{recursion(name + '_all', base, 'simple', bound, seed)},
{name} AS (SELECT * EXCLUDE (m) FROM (SELECT *, min(len) OVER (PARTITION BY src, dst) AS m FROM {name}_all) WHERE len = m)"""
    first, more = _MODES[mode]
    return f"""{name} AS (
  SELECT src, dst, 1 AS len, [src, dst] AS nodes, [eid] AS edges FROM {base} WHERE {first} AND {seed}
  UNION ALL SELECT p.src, e.dst, p.len + 1, list_append(p.nodes, e.dst), list_append(p.edges, e.eid)
  FROM {name} p JOIN {base} e ON p.dst = e.src WHERE p.len < {bound} AND {more})"""


def singles(name: str, base: str) -> str:
    return f"{name} AS (SELECT src, dst, 1 AS len, [src, dst] AS nodes, [eid] AS edges FROM {base})"


def concat(name: str, a: str, b: str) -> str:
    return f"{name} AS (SELECT a.src, b.dst, a.len + b.len AS len, list_concat(a.nodes, b.nodes[2:]) AS nodes, list_concat(a.edges, b.edges) AS edges FROM {a} a JOIN {b} b ON a.dst = b.src)"


OUT = "src, dst, CAST(len AS BIGINT) AS len, array_to_string(nodes::VARCHAR[], '-') AS nodes_txt, array_to_string(edges::VARCHAR[], '-') AS edges_txt"
TIE = "len, nodes, edges"


def final(ctes: list[str], body: str, columns: str = OUT) -> str:
    """body: what follows FROM."""
    return "WITH RECURSIVE " + ",\n".join(ctes) + f"\nSELECT {columns} FROM {body}"


_KEYS = {"": ("1", "1"), "S": ("src", "1"), "T": ("dst", "1"), "L": ("1", "len"), "ST": ("src, dst", "1"), "SL": ("src", "len"), "TL": ("dst", "len"), "STL": ("src, dst", "len")}


def projected(base: str, letters: str, order: str, p, g, a, desc: str = "") -> str:
    """A subquery of base cut to p partitions, g groups, a paths."""
    part, group = _KEYS[letters]
    way = lambda x: " DESC" if x in desc else ""
    min_p, min_g = f"min(len) OVER (PARTITION BY {part})", f"min(len) OVER (PARTITION BY {part}, {group})"
    op, og, oa = (min_p if "P" in order else "1"), (min_g if "G" in order else "1"), ("len" if "A" in order else "1")
    valued = f"(SELECT *, {op} AS op, {og} AS og, {oa} AS oa FROM {base})"
    ranked = f"(SELECT *, dense_rank() OVER (ORDER BY op{way('P')}, {part}) AS rp, dense_rank() OVER (PARTITION BY {part} ORDER BY og{way('G')}, {group}) AS rg, row_number() OVER (PARTITION BY {part}, {group} ORDER BY oa{way('A')}, {TIE}) AS ra FROM {valued})"
    tests = [f"{r} <= {k}" for r, k in (("rp", p), ("rg", g), ("ra", a)) if k != "*"]
    return f"(SELECT * FROM {ranked} WHERE {' AND '.join(tests) or 'true'})"

"""SQL over the same tables for the path engine's queries: path sets by recursion, selectors by windows."""

from __future__ import annotations

from pathweave import automaton, regex
from pathweave.modes import parse_mode

HOP = """edges AS MATERIALIZED (SELECT * FROM (SELECT user_id AS src, {label} AS label, lead(user_id) OVER (ORDER BY ts, event_id) AS dst, event_id AS eid, ts FROM events) WHERE dst IS NOT NULL {where}),
nodes AS MATERIALIZED (SELECT DISTINCT user_id AS id FROM events)"""
_ENDS = "nodes AS MATERIALIZED (SELECT src AS id FROM edges UNION SELECT dst FROM edges)"
STAR = f"""edges AS MATERIALIZED (
 SELECT 'C:' || o_custkey AS src, 'placed' AS label, 'O:' || o_orderkey AS dst, 'placed|C:' || o_custkey || '|O:' || o_orderkey AS eid FROM orders
 UNION ALL SELECT DISTINCT 'O:' || l_orderkey, 'contains', 'P:' || l_partkey, 'contains|' || l_orderkey || '|' || l_linenumber || '|' || l_partkey || '|' || l_suppkey FROM lineitem
 UNION ALL SELECT DISTINCT 'S:' || l_suppkey, 'supplies', 'P:' || l_partkey, 'supplies|S:' || l_suppkey || '|P:' || l_partkey FROM lineitem
 UNION ALL SELECT 'C:' || c_custkey, 'livesin', 'N:' || c_nationkey, 'livesin|C:' || c_custkey || '|N:' || c_nationkey FROM customer
 UNION ALL SELECT 'S:' || s_suppkey, 'basedin', 'N:' || s_nationkey, 'basedin|S:' || s_suppkey || '|N:' || s_nationkey FROM supplier
 UNION ALL SELECT 'N:' || n_nationkey, 'partof', 'R:' || n_regionkey, 'partof|N:' || n_nationkey || '|R:' || n_regionkey FROM nation), {_ENDS}"""
TRADE = f"""edges AS MATERIALIZED (SELECT DISTINCT CAST(c_nationkey AS BIGINT) AS src, l_returnflag AS label, CAST(s_nationkey AS BIGINT) AS dst, l_returnflag || '|' || lpad(CAST(c_nationkey AS VARCHAR), 2, '0') || '|' || lpad(CAST(s_nationkey AS VARCHAR), 2, '0') AS eid
 FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey), {_ENDS}"""
LINK = f"""edges AS MATERIALIZED (SELECT *, label || '|' || src || '|' || dst AS eid FROM (
 SELECT DISTINCT 'g:' || page_id AS src, 'links' AS label, 't:' || t AS dst FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS t FROM pages)
 UNION ALL SELECT DISTINCT 'g:' || page_id, 'on', 'h:' || regexp_extract(url, '://([^/?#]*)', 1) FROM pages)), {_ENDS}"""
TURN = f"""edges AS MATERIALIZED (SELECT * FROM (SELECT conv_id || ':' || turn AS src, role AS label, lead(conv_id || ':' || turn) OVER (PARTITION BY conv_id ORDER BY turn) AS dst, conv_id || ':' || turn AS eid FROM conversations) WHERE dst IS NOT NULL),
nodes AS MATERIALIZED (SELECT conv_id || ':' || turn AS id FROM conversations)"""
TRIPLES = f"""edges AS MATERIALIZED (SELECT s AS src, p AS label, o AS dst, s || ' ' || p || ' ' || o AS eid FROM (
 SELECT 'C:' || c_custkey AS s, 'livesin' AS p, 'N:' || c_nationkey AS o FROM customer
 UNION SELECT 'S:' || s_suppkey, 'basedin', 'N:' || s_nationkey FROM supplier UNION SELECT 'N:' || n_nationkey, 'partof', 'R:' || n_regionkey FROM nation)), {_ENDS}"""


def diamond(n: int) -> str:
    return f"""edges AS MATERIALIZED (SELECT 3 * b.i + s AS src, 'a' AS label, 3 * b.i + d AS dst, 4 * b.i + k AS eid FROM (SELECT CAST(unnest(range({n})) AS BIGINT) AS i) b, (VALUES (0, 1, 0), (0, 2, 1), (1, 3, 2), (2, 3, 3)) v(s, d, k)), {_ENDS}"""


def order_diamond(n: int) -> str:
    return f"""chain AS MATERIALIZED (SELECT *, lead(k) OVER (ORDER BY k) AS nxt FROM (SELECT l_orderkey AS k, min(l_linenumber) AS x, max(l_linenumber) AS y FROM lineitem GROUP BY 1 HAVING min(l_linenumber) < max(l_linenumber) ORDER BY 1 LIMIT {n + 1})),
lines AS (SELECT k, nxt, unnest([x, y]) AS m FROM chain WHERE nxt IS NOT NULL),
edges AS MATERIALIZED (SELECT *, label || '|' || src || '|' || dst AS eid FROM (SELECT 'O:' || k AS src, 'a' AS label, 'L:' || k || ':' || m AS dst FROM lines UNION ALL SELECT 'L:' || k || ':' || m, 'a', 'O:' || nxt FROM lines)), {_ENDS}"""


def hop(label: str | None = None, days: int | None = None) -> str:
    return HOP.format(label="event_type" if label is None else f"'{label}'", where="" if days is None else f"AND ts < TIMESTAMP '2024-01-01' + INTERVAL {days} DAY")


GRAPHS = {"star": STAR, "trade": TRADE, "link": LINK, "turn": TURN, "triples": TRIPLES}
#: The node in the middle by (degree, id).
MEDIAN = "(SELECT id FROM (SELECT id, row_number() OVER (ORDER BY d, id) AS rn, count(*) OVER () AS n FROM (SELECT id, coalesce(c, 0) AS d FROM nodes LEFT JOIN (SELECT v, count(*) AS c FROM (SELECT src AS v FROM edges UNION ALL SELECT dst FROM edges) GROUP BY v) ON v = id)) WHERE rn = (n + 1) // 2)"


def graph_sql(name: str) -> str:
    kind, _, arg = name.partition(":")
    if kind == "hop":
        return hop(arg or None)
    if kind == "slice":
        return hop(days=int(arg))
    if kind == "order_diamond":
        return order_diamond(int(arg))
    return diamond(int(arg)) if kind == "diamond" else GRAPHS[kind]


#: The node without an edge in, and the one without an edge out, of a graph with one of each.
ENDS = {"source": "(SELECT DISTINCT src FROM edges WHERE src NOT IN (SELECT dst FROM edges))", "sink": "(SELECT DISTINCT dst FROM edges WHERE dst NOT IN (SELECT src FROM edges))"}


def _value(v) -> str:
    if v in ENDS:
        return ENDS[v]
    return MEDIAN if v == "median" else str(v) if isinstance(v, int) else "'" + v + "'"


def _head(graph: str, a, start) -> str:
    delta = ", ".join(f"({q}, '{s[0]}', {str(s[1]).lower()}, {r})" for q, s, r in a.delta)
    where = "" if start is None else f"WHERE id = {_value(start)}"
    return f"""WITH RECURSIVE {graph_sql(graph)},
delta(q, label, inv, q2) AS (VALUES {delta}),
adj AS MATERIALIZED (SELECT src AS node, label, false AS inv, dst AS nxt, eid FROM edges UNION ALL SELECT dst, label, true, src, eid FROM edges),
starts AS (SELECT DISTINCT id FROM nodes {where})"""


_JOIN = "JOIN delta d ON d.q = p.q JOIN adj a ON a.node = p.node AND a.label = d.label AND a.inv = d.inv"


def endpoints(graph: str, pattern: str, start=None, end=None) -> str:
    a = automaton.glushkov(regex.parse(pattern))
    finals = ", ".join(map(str, sorted(a.finals)))
    at_end = "" if end is None else f"AND node = {_value(end)}"
    return f"""{_head(graph, a, start)},
p(s, node, q) AS (SELECT id, id, {a.initial} FROM starts UNION SELECT p.s, a.nxt, d.q2 FROM p {_JOIN})
SELECT DISTINCT s AS src, node AS dst FROM p WHERE q IN ({finals}) {at_end}"""


def _selected(mode) -> str:
    return {"ALL": "true", "ANY": "rn = 1", "ANY SHORTEST": "rn = 1", "ALL SHORTEST": "g = 1", "ANY K": f"rn <= {mode.k}", "SHORTEST K": f"rn <= {mode.k}", "SHORTEST K GROUPS": f"g <= {mode.k}"}[mode.selector]


_VALID = {
    "WALK": "true",
    "TRAIL": "NOT list_contains(p.eids, a.eid)",
    "ACYCLIC": "NOT list_contains(p.nodes, a.nxt)",
    "SIMPLE": "NOT (p.len > 0 AND p.node = p.s) AND (NOT list_contains(p.nodes, a.nxt) OR a.nxt = p.s)",
}
_PATHS = """f AS (SELECT DISTINCT s, node, len, eids FROM p WHERE q IN ({finals}) {at_end}),
r AS (SELECT *, row_number() OVER (PARTITION BY s, node ORDER BY len, eids) AS rn, dense_rank() OVER (PARTITION BY s, node ORDER BY len) AS g FROM f)
SELECT s AS src, node AS dst, CAST(len AS INTEGER) AS length, array_to_string(eids, '>') AS path FROM r WHERE {selected}"""


def paths(graph: str, mode: str, pattern: str, start=None, end=None, k: int | None = None) -> str:
    """Path sets by enumeration: any restrictor; walks of expressions without a star."""
    m, a = parse_mode(mode, k), automaton.glushkov(regex.parse(pattern)).unambiguous()
    at_end = "" if end is None else f"AND node = {_value(end)}"
    return f"""{_head(graph, a, start)},
p(s, node, q, len, eids, nodes) AS (SELECT id, id, {a.initial}, 0, (SELECT list(eid) FROM edges WHERE false), [id] FROM starts
 UNION ALL SELECT p.s, a.nxt, d.q2, p.len + 1, list_append(coalesce(p.eids, []), a.eid), list_append(p.nodes, a.nxt) FROM p {_JOIN} WHERE {_VALID[m.restrictor].replace("p.eids", "coalesce(p.eids, [])")}),
{_PATHS.format(finals=", ".join(map(str, sorted(a.finals))), at_end=at_end, selected=_selected(m)).replace("array_to_string(eids, '>')", "coalesce(array_to_string(eids, '>'), '')")}"""


def shortest(graph: str, mode: str, pattern: str, start=None, end=None, depth: int = 12) -> str:
    """Shortest walks of any expression: distances of product keys first (up to a depth), then paths along them."""
    m, a = parse_mode(mode), automaton.glushkov(regex.parse(pattern)).unambiguous()
    at_end = "" if end is None else f"AND node = {_value(end)}"
    return f"""{_head(graph, a, start)},
reach(s, node, q, d) AS (SELECT id, id, {a.initial}, 0 FROM starts UNION SELECT p.s, a.nxt, d.q2, p.d + 1 FROM reach p {_JOIN} WHERE p.d < {depth}),
dist AS MATERIALIZED (SELECT s, node, q, min(d) AS d FROM reach GROUP BY ALL),
p(s, node, q, len, eids) AS (SELECT id, id, {a.initial}, 0, (SELECT list(eid) FROM edges WHERE false) FROM starts
 UNION ALL SELECT p.s, a.nxt, d.q2, p.len + 1, list_append(coalesce(p.eids, []), a.eid) FROM p {_JOIN} JOIN dist t ON t.s = p.s AND t.node = a.nxt AND t.q = d.q2 AND t.d = p.len + 1),
{_PATHS.format(finals=", ".join(map(str, sorted(a.finals))), at_end=at_end, selected=_selected(m)).replace("array_to_string(eids, '>')", "coalesce(array_to_string(eids, '>'), '')")}"""


def words(graph: str, mode: str, rx: str, max_length: int, start=None, k: int | None = None) -> str:
    """Path sets without any automaton: paths of the restrictor up to a length, their labels' first letters as a word, and the word
    tested by DuckDB's own regular expressions."""
    m = parse_mode(mode, k)
    where = "" if start is None else f"WHERE id = {_value(start)}"
    valid = _VALID[m.restrictor].replace("a.nxt", "a.dst")
    tail = _PATHS.split("\nr AS")[1].format(finals="", at_end="", selected=_selected(m)).replace("array_to_string(eids, '>')", "coalesce(array_to_string(eids, '>'), '')")
    return f"""WITH RECURSIVE {graph_sql(graph)},
p(s, node, len, eids, nodes, w) AS (SELECT id, id, 0, (SELECT list(eid) FROM edges WHERE false), [id], '' FROM (SELECT DISTINCT id FROM nodes {where})
 UNION ALL SELECT p.s, a.dst, p.len + 1, list_append(coalesce(p.eids, []), a.eid), list_append(p.nodes, a.dst), p.w || left(a.label, 1) FROM p JOIN edges a ON a.src = p.node
 WHERE p.len < {max_length} AND {valid.replace("p.eids", "coalesce(p.eids, [])")}),
f AS (SELECT s, node, len, eids FROM p WHERE regexp_full_match(w, '{rx}')),
r AS{tail}"""

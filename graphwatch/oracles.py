"""DuckDB SQL for the engine's queries, written from the tables and the patterns, not from join trees."""

from __future__ import annotations

from graphwatch.model import QueryEdge, QueryGraph
from graphwatch.sources.graphs import BANDS, BITS, CODES


def _vid(kind: str, key: str) -> str:
    return f"{CODES[kind] << BITS} + {key}"


_K = "cast(json_extract_string(props, '$.k') AS BIGINT)"


def _case(value: str) -> str:
    return "CASE " + " ".join(f"WHEN {value} < {c} THEN 'k{i}'" for i, c in enumerate(BANDS)) + f" ELSE 'k{len(BANDS)}' END"


FACET = f"""
facet_raw AS (
 SELECT DISTINCT {_vid("order", "l_orderkey")} AS src, {_vid("part", "l_partkey")} AS dst, 'part' AS etype, o_orderdate AS ts FROM lineitem JOIN orders ON l_orderkey = o_orderkey
 UNION ALL SELECT DISTINCT {_vid("order", "l_orderkey")}, {_vid("supplier", "l_suppkey")}, 'supplier', o_orderdate FROM lineitem JOIN orders ON l_orderkey = o_orderkey
 UNION ALL SELECT {_vid("order", "o_orderkey")}, {_vid("customer", "o_custkey")}, 'customer', o_orderdate FROM orders JOIN customer ON o_custkey = c_custkey
 UNION ALL SELECT {_vid("order", "o_orderkey")}, {_vid("nation", "c_nationkey")}, 'nation', o_orderdate FROM orders JOIN customer ON o_custkey = c_custkey),
edges AS MATERIALIZED (SELECT row_number() OVER (ORDER BY ts, src, etype, dst) - 1 AS eid, src, dst, etype, ts FROM facet_raw)"""


def _host(kind: str) -> str:
    return f"""
host_raw AS (SELECT event_id, user_id AS src, {_K} AS dst, value, event_type, ts FROM events),
edges AS MATERIALIZED (SELECT row_number() OVER (ORDER BY event_id) - 1 AS eid, src, dst, {kind} AS etype, ts FROM host_raw WHERE src <> dst)"""


HOST = _host(_case("value"))
COMMUNITY = _host("CASE WHEN value >= 250 THEN 'c' || (event_id % 7) WHEN src % 7 = dst % 7 THEN 'c' || (src % 7) WHEN value < 60 THEN 'x0' WHEN value < 120 THEN 'x1' ELSE 'x2' END")
TRADE = f"""
edges AS MATERIALIZED (SELECT row_number() OVER (ORDER BY l_shipdate, l_orderkey, l_partkey, l_suppkey, l_linenumber) - 1 AS eid,
 {_vid("supplier", "l_suppkey")} AS src, {_vid("customer", "o_custkey")} AS dst, l_returnflag || '_' || l_linestatus AS etype, l_shipdate AS ts
 FROM lineitem JOIN orders ON l_orderkey = o_orderkey)"""


def _category(table: str, kind: str, key: str, value: str, target: str, name: str, ts: str = "TIMESTAMP '1970-01-01'") -> str:
    return f"SELECT {_vid(kind, key)} AS src, {_vid(target, f'(dense_rank() OVER (ORDER BY {value}) - 1)')} AS dst, '{name}' AS etype, {ts} AS ts FROM {table}"


_T0 = "TIMESTAMP '1970-01-01'"
_SOCIAL = [
    f"SELECT {_vid('customer', 'c_custkey')} AS src, {_vid('nation', 'c_nationkey')} AS dst, 'in_nation' AS etype, {_T0} AS ts FROM customer",
    f"SELECT {_vid('supplier', 's_suppkey')}, {_vid('nation', 's_nationkey')}, 'from_nation', {_T0} FROM supplier",
    f"SELECT {_vid('nation', 'n_nationkey')}, {_vid('region', 'n_regionkey')}, 'in_region', {_T0} FROM nation",
    _category("customer", "customer", "c_custkey", "c_mktsegment", "segment", "segment"),
    _category("part", "part", "p_partkey", "p_brand", "brand", "brand"),
    _category("part", "part", "p_partkey", "p_type", "ptype", "ptype"),
    _category("documents", "document", "doc_id", "source", "source", "source"),
    _category("documents", "document", "doc_id", "lang", "lang", "lang"),
    f"SELECT {_vid('document', 'doc_id')}, {_vid('quality', 'quality')}, 'quality', {_T0} FROM labels",
    f"SELECT {_vid('document', 'doc_id')}, {_vid('toxic', 'toxic')}, 'toxic', {_T0} FROM labels",
    _category("pages", "page", "page_id", "regexp_extract(url, '://([^/?#]*)', 1)", "site", "site"),
    f"SELECT {_vid('conversation', 'conv_id')}, {_vid('turn', 'conv_id * 65536 + turn')}, 'turn_' || role, {_T0} FROM conversations",
    f"SELECT {_vid('customer', 'o_custkey')}, {_vid('order', 'o_orderkey')}, 'places', o_orderdate FROM orders",
    _category("orders", "order", "o_orderkey", "o_orderpriority", "priority", "prio", "o_orderdate"),
    _category("orders", "order", "o_orderkey", "o_orderstatus", "status", "status", "o_orderdate"),
    f"SELECT {_vid('order', 'l_orderkey')}, {_vid('part', 'l_partkey')}, 'has_' || l_returnflag || l_linestatus, l_shipdate FROM lineitem",
    f"SELECT {_vid('supplier', 'l_suppkey')}, {_vid('order', 'l_orderkey')}, 'ships_' || l_returnflag || l_linestatus, l_shipdate FROM lineitem",
    f"SELECT {_vid('customer', 'user_id')}, {_vid('object', _K)}, event_type, ts FROM events",
]
SOCIAL = f"""
social_raw AS ({" UNION ALL ".join(_SOCIAL)}),
edges AS MATERIALIZED (SELECT row_number() OVER (ORDER BY ts, etype, src, dst) - 1 AS eid, src, dst, etype, ts FROM social_raw)"""

GRAPHS = {"facet": FACET, "host": HOST, "community": COMMUNITY, "trade": TRADE, "social": SOCIAL}


def _side(graph: QueryGraph, e: QueryEdge) -> str:
    """The edges of one query edge: kind and predicates only."""
    rows, tests = "edges", [f"etype = '{e.etype}'"]
    for v, c in ((e.src, "src"), (e.dst, "dst")):
        if p := graph.predicate(v):
            rows = f"(SELECT *, {c} AS vid FROM (SELECT eid, src, dst, etype, ts FROM {rows}) WHERE {' AND '.join(tests)})"
            tests = [f"({p})"]
    if e.predicate:
        tests.append(f"({e.predicate})")
    return f"(SELECT eid, src, dst, ts FROM {rows} WHERE {' AND '.join(tests)}) {e.name}"


def matches(graph: QueryGraph, extra: str = "", within: str | None = None) -> str:
    """A join of the edges with themselves, one copy for each query edge; all vertices and all edges differ.

    Written as connected joins in the pattern's own order, so that it is quick without a join reordering too.
    """
    if len(graph.edges) > 4 and not extra and not within:
        return _step_by_step(graph)
    at: dict[str, str] = {}
    done: list[QueryEdge] = []
    left, sources, last = list(graph.edges), "", []
    while left:
        e = next((e for e in left if not at or set(e.ends) & set(at)), left[0])
        left.remove(e)
        tests = []
        for v, c in ((e.src, f"{e.name}.src"), (e.dst, f"{e.name}.dst")):
            if v in at:
                tests.append(f"{c} = {at[v]}")
            else:
                tests += [f"{c} <> {x}" for x in at.values()]
                at[v] = c
        tests += [f"{e.name}.eid <> {o.name}.eid" for o in done if o.etype == e.etype]
        done.append(e)
        if sources:
            sources += f" JOIN {_side(graph, e)} ON {' AND '.join(tests)}"
        else:
            sources, last = _side(graph, e), tests
    if extra:
        last.append(extra)
    if within and len(graph.edges) > 1:
        times = ", ".join(f"{e.name}.ts" for e in graph.edges)
        last.append(f"greatest({times}) <= least({times}) + INTERVAL {within}")
    eids = ", ".join(f"{e.name}.eid" for e in graph.edges)
    columns = [f"CAST({at[v]} AS BIGINT) AS v_{v}" for v in graph.vertex_names] + [f"{e.name}.eid AS e_{e.name}" for e in graph.edges]
    return f"SELECT {', '.join(columns)}, greatest({eids}) AS last_eid FROM {sources}{' WHERE ' + ' AND '.join(last) if last else ''}"


def _step_by_step(graph: QueryGraph) -> str:
    """The same for many edges: every join is kept as a table, as the optimizer may begin a longer chain at a hub."""
    seen: list[str] = []
    done: list[QueryEdge] = []
    left, steps = list(graph.edges), []
    while left:
        e = next((e for e in left if not seen or set(e.ends) & set(seen)), left[0])
        left.remove(e)
        on, new = [], []
        for v, c in ((e.src, f"{e.name}.src"), (e.dst, f"{e.name}.dst")):
            if v in seen:
                on.append(f"{c} = s.v_{v}")
            else:
                on += [f"{c} <> s.v_{x}" for x in seen]
                new.append((v, c))
        on += [f"{e.name}.eid <> s.e_{o.name}" for o in done if o.etype == e.etype]
        columns = ", ".join([*([] if not steps else ["s.*"]), *[f"{c} AS v_{v}" for v, c in new], f"{e.name}.eid AS e_{e.name}"])
        source = f"{_side(graph, e)} WHERE {e.name}.src <> {e.name}.dst" if not steps else f"step{len(steps) - 1} s JOIN {_side(graph, e)} ON {' AND '.join(on)}"
        steps.append(f"step{len(steps)} AS MATERIALIZED (SELECT {columns} FROM {source})")
        seen += [v for v, _ in new]
        done.append(e)
    columns = [f"CAST(v_{v} AS BIGINT) AS v_{v}" for v in graph.vertex_names] + [f"e_{e.name}" for e in graph.edges]
    eids = ", ".join(f"e_{e.name}" for e in graph.edges)
    return f"SELECT * FROM (WITH {', '.join(steps)} SELECT {', '.join(columns)}, greatest({eids}) AS last_eid FROM step{len(steps) - 1})"


def diamond_count(a: str, b: str) -> str:
    """Two articles that share both facets: of the c articles of a pair of facets, c * (c - 1) ordered pairs."""
    pairs = f"SELECT one.dst AS x, two.dst AS y, count(*) AS c FROM (SELECT src, dst FROM edges WHERE etype = '{a}') one JOIN (SELECT src, dst FROM edges WHERE etype = '{b}') two ON one.src = two.src AND one.dst <> two.dst GROUP BY 1, 2"
    return f"SELECT CAST(coalesce(sum(c * (c - 1)), 0) AS BIGINT) AS n FROM ({pairs})"


def over(graph_name: str, body: str, ctes: str = "") -> str:
    return f"WITH {GRAPHS[graph_name]}{', ' + ctes if ctes else ''} {body}"


INCIDENCE = "inc AS (SELECT src AS v, 'o:' || etype AS sig, dst AS u, eid FROM edges UNION ALL SELECT dst, 'i:' || etype, src, eid FROM edges)"
PATHS = INCIDENCE + """, cnt AS (SELECT v, sig, count(*) AS n FROM inc GROUP BY v, sig),
paths AS (SELECT a.sig AS sig1, b.sig AS sig2, CAST(sum(CASE WHEN a.sig = b.sig THEN a.n * (a.n - 1) // 2 ELSE a.n * b.n END) AS BIGINT) AS cnt
 FROM cnt a JOIN cnt b ON a.v = b.v AND a.sig <= b.sig GROUP BY 1, 2 HAVING sum(CASE WHEN a.sig = b.sig THEN a.n * (a.n - 1) // 2 ELSE a.n * b.n END) > 0)"""
#: Pairs made one by one, for the strict count.
STRICT = INCIDENCE + """, paths AS (SELECT a.sig AS sig1, b.sig AS sig2, count(*) AS cnt FROM inc a JOIN inc b ON a.v = b.v
 AND (a.sig < b.sig OR a.sig = b.sig AND a.eid < b.eid) WHERE a.u <> b.u AND a.u <> a.v AND b.u <> b.v GROUP BY 1, 2)"""

"""Further queries: other shapes and orders, counters, per-edge and index baselines, random groups, and the operators around the methods."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphwatch import oracles as sql
from graphwatch.api import watch
from graphwatch.catalogue import GRAPHS, Query, _group_xi, _tree, _xi_rows
from graphwatch.functions import user
from graphwatch.model import JoinTree, Leaf, QueryGraph, QueryVertex, pattern
from graphwatch.operators import baselines, matching, shapes, stats
from graphwatch.operators.delta import AdaptiveMatcher, DeltaMatcher, advance_all
from graphwatch.plans import cutting, workload
from graphwatch.sources import graphs

_Q: dict[str, Query] = {}
_SQL: dict[str, str] = {}


def _add(name: str, graph: str, query, body: str | None, ctes: str = "") -> None:
    _Q[name] = lambda s, d: query(GRAPHS[graph](s, d))
    if body:
        _SQL[name] = sql.over(graph, body, ctes)


_P2, _P3, _P4 = (workload.HOST[f"host_path{k}"] for k in (2, 3, 4))
_ONE = JoinTree(tuple(Leaf((x,)) for x in _P3.edges))
_TWO = JoinTree((Leaf(_P3.edges[:2]), Leaf(_P3.edges[2:])))

# Shapes.

_add("bushy_host_path4", "host", lambda e: shapes.run_bushy(e, JoinTree(tuple(Leaf((x,)) for x in _P4.edges)), _P4), sql.matches(_P4))
_add("n_ary_host_path3", "host", lambda e: shapes.run_n_ary(e, _ONE, _P3), sql.matches(_P3))
_add("cartesian_small", "host", lambda e: matching.run_tree(e, _tree(e, pattern("a -k6> b", "c -k5> d"), allow_cartesian=True), pattern("a -k6> b", "c -k5> d")), sql.matches(pattern("a -k6> b", "c -k5> d")).replace(" ON ", " ON true AND ", 1))

# Types and labels of vertices, from a table of vertices.

_LABELLED = pattern("c -places> o", "o -has_AF> p")
_LABELLED = QueryGraph(_LABELLED.edges, (QueryVertex("c", "customer", label="^BUILD"), QueryVertex("p", "part", label="^ECON")))
_Q["vertex_label_path"] = lambda s, d: matching.run_tree((e := graphs.social_graph(s, d)), _tree(e, _LABELLED), _LABELLED, gated=True, vertices=graphs.social_vertices(s, d))
_code = lambda t: graphs.CODES[t] << graphs.BITS
_SQL["vertex_label_path"] = sql.over("social", f"SELECT m.* FROM ({sql.matches(QueryGraph(_LABELLED.edges))}) m JOIN customer ON v_c = {_code('customer')} + c_custkey AND regexp_matches(c_mktsegment, '^BUILD') JOIN part ON v_p = {_code('part')} + p_partkey AND regexp_matches(p_type, '^ECON')")
_ROOTED = pattern("r -k1> a", "r -k2> b", "a -k3> c", r="vid < 40", c="vid BETWEEN 50 AND 60")
_add("labeled_tree__gated1", "host", lambda e: watch(e, _ROOTED, "gated1", prefix=None), sql.matches(_ROOTED))

# What a run does.

_n = lambda kind: f"(SELECT count(*) FROM edges WHERE etype = '{kind}')"
_p2, _p3 = (f"(SELECT count(*) FROM ({sql.matches(p)}))" for p in (_P2, _P3))
_g0, _g1 = "(SELECT count(*) FROM edges WHERE etype = 'k0' AND src IN (SELECT dst FROM edges WHERE etype = 'k4'))", "(SELECT count(*) FROM edges WHERE etype = 'k1' AND src IN (SELECT v_c FROM p))"
_seen = "(SELECT count(*) FROM (SELECT dst FROM edges WHERE etype = 'k4') a JOIN (SELECT src FROM edges WHERE etype = 'k0') b ON a.dst = b.src)"


def _counter_rows(rows: list[tuple[str, ...]]) -> str:
    names = "searches neighbours stored probes results".split()
    return " UNION ALL ".join(f"SELECT {i}::INTEGER AS leaf, " + ", ".join(f"CAST({x} AS BIGINT) AS {n}" for x, n in zip(r, names, strict=True)) for i, r in enumerate(rows))


for _name, _t, _gated, _rows in (
    ("eager1", _ONE, False, [(_n("k4"), "0", _n("k4"), "0", _n("k4")), (_n("k0"), "0", _n("k0"), f"{_n('k0')} + {_n('k4')}", _p2), (_n("k1"), "0", _n("k1"), f"{_n('k1')} + {_p2}", _p3)]),
    ("gated1", _ONE, True, [(_n("k4"), "0", _n("k4"), "0", _n("k4")), (_g0, "0", _g0, f"{_g0} + {_n('k4')}", _p2), (_g1, "0", _g1, f"{_g1} + {_p2}", _p3)]),
    ("eager2", _TWO, False, [(f"{_n('k4')} + {_n('k0')}", _seen, _p2, "0", _p2), (_n("k1"), "0", _n("k1"), f"{_n('k1')} + {_p2}", _p3)]),
    ("gated2", _TWO, True, [(f"{_n('k4')} + {_n('k0')}", _seen, _p2, "0", _p2), (_g1, "0", _g1, f"{_g1} + {_p2}", _p3)]),
):
    _add(f"counters_{_name}", "host", lambda e, t=_t, g=_gated: matching.tree_counters(e, t, _P3, g), _counter_rows(_rows), f"p AS ({sql.matches(_P2)})")


def _q_errors(e: DataFrame) -> DataFrame:
    """node, estimate (the rarer side, from kinds alone), actual, q_error of the left-deep tree of single edges."""
    known, rows, estimate = cutting.collect_statistics(e), [], None
    actual = {r.leaf: r.results for r in matching.tree_counters(e, _ONE, _P3).collect()}
    for i, leaf in enumerate(_ONE.leaves):
        estimate = known.frequency(leaf) if estimate is None else min(estimate, known.frequency(leaf))
        rows.append((i, estimate, actual[i], round(cutting.q_error(estimate, actual[i]), 6)))
    return e.sparkSession.createDataFrame(rows, "node int, estimate long, actual long, q_error double")


_add("qerror", "host", _q_errors, f"SELECT *, round(greatest(greatest(estimate, 1)::DOUBLE / greatest(actual, 1), greatest(actual, 1)::DOUBLE / greatest(estimate, 1)), 6) AS q_error FROM (SELECT 0::INTEGER AS node, {_n('k4')} AS estimate, {_n('k4')} AS actual UNION ALL SELECT 1::INTEGER, least({_n('k4')}, {_n('k0')}), {_p2} UNION ALL SELECT 2::INTEGER, least({_n('k4')}, {_n('k0')}, {_n('k1')}), {_p3})")


def _hub_searches(e: DataFrame) -> DataFrame:
    """Earlier edges that must be looked at when a nation becomes enabled by an article's pair of nation and part."""
    g = workload.facet_diamond("nation", "part")
    gates = matching.gate_rows(matching.leaf_matches(e, Leaf(g.edges[:2])), 1)
    found = matching.back_search(e, gates, g.edges[2], 1)
    return found.filter(F.call_function("shiftright", "vid", F.lit(graphs.BITS)) == graphs.CODES["nation"]).groupBy("vid").agg(F.count("*").alias("n"))


_add("hub_back_search", "facet", _hub_searches, "SELECT e.dst AS vid, count(*) AS n FROM edges e JOIN s ON e.dst = s.x WHERE e.etype = 'nation' AND e.eid < s.since GROUP BY 1", "s AS (SELECT a.dst AS x, min(greatest(a.eid, b.eid)) AS since FROM (SELECT * FROM edges WHERE etype = 'nation') a JOIN (SELECT * FROM edges WHERE etype = 'part') b ON a.src = b.src GROUP BY 1)")

# Baselines that search again.

_add("host_path2__per_edge", "host", lambda e: baselines.rematch_per_edge(e, _P2), "SELECT m.*, last_eid AS reported, count(*) OVER (ORDER BY last_eid RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS found FROM m", f"m AS ({sql.matches(_P2)})")
_add("host_path2__backtrack", "host", lambda e: baselines.backtrack_matches(e, _P2), sql.matches(_P2))
_add("host_path2__indexed", "host", lambda e: baselines.indexed_rematch(e, _P2, 2, e.count()), sql.matches(_P2))
_add("periodic_redundant", "host", lambda e: baselines.rematch_every(e, _P3, 5, e.count(), counted=True), "SELECT b AS batch, (SELECT count(*) FROM m WHERE last_eid < (b + 1) * size) AS found, (SELECT count(*) FROM m WHERE last_eid < b * size) AS redundant FROM (SELECT unnest(range(5)) AS b, (SELECT (count(*) + 4) // 5 FROM edges) AS size)", f"m AS ({sql.matches(_P3)})")

# Batches: pieces of two edges, a bound in time with state that is dropped, a plan that is changed on the way.

_add("host_path3__delta4_gated2", "host", lambda e: advance_all(e, _TWO, _P3, 4, e.count(), gated=True), sql.matches(_P3))


def _bounded(e: DataFrame) -> DataFrame:
    n, matcher = e.count(), DeltaMatcher(JoinTree(_ONE.leaves[:2]), _P2, gated=True, within="'2' DAY", fanout=2)
    for b in range(4):
        matcher.advance(e.filter((F.col("eid") * 4 >= b * n) & (F.col("eid") * 4 < (b + 1) * n)))
    return matcher.snapshot()


_add("delta_within", "host", _bounded, sql.matches(_P2, within="'2' DAY"))


def _replanned(e: DataFrame) -> DataFrame:
    """Starts with the commonest piece; after two batches the statistics ask for another cut, and the state moves."""
    n = e.count()
    recut = lambda edges: cutting.cut_pattern(_P3, cutting.collect_statistics(edges))
    matcher = AdaptiveMatcher(JoinTree(tuple(Leaf((x,)) for x in reversed(_P3.edges))), _P3, recut)
    for b in range(4):
        matcher.advance(e.filter((F.col("eid") * 4 >= b * n) & (F.col("eid") * 4 < (b + 1) * n)))
    return matcher.snapshot()


_add("replan_migrate", "host", _replanned, sql.matches(_P3))

# Random groups, and the spread of the relative selectivity.

for _shape, _path in (("paths", True), ("trees", False)):
    _group = workload.random_social(3, 4, _path)

    def _counts(e: DataFrame, group=_group) -> DataFrame:
        known, out = cutting.collect_statistics(e), None
        for name, g in group.items():
            choice = cutting.choose_strategy(g, known)
            n = matching.run_tree(e, choice.tree, g, gated=True).agg(F.count("*").alias("n")).select(F.lit(name).alias("pattern"), "n")
            out = n if out is None else out.unionByName(n)
        return out

    _add(f"social_random_{_shape}", "social", _counts, " UNION ALL ".join(f"SELECT '{k}' AS pattern, count(*) AS n FROM ({sql.matches(g)})" for k, g in _group.items()))

_RANDOM = {f"path{i:03}": workload.random_path(4, [f"k{k}" for k in range(7)], i) for i in range(100)}


def _pairs_of(g: QueryGraph) -> list[tuple[str, str]]:
    return [cutting.pair_signature(a, b, v) for i, a in enumerate(g.edges) for b in g.edges[i + 1 :] for v in set(a.ends) & set(b.ends)]


def _kept_queries(e: DataFrame) -> DataFrame:
    known = cutting.collect_statistics(e)
    return e.sparkSession.createDataFrame([(k,) for k, g in _RANDOM.items() if workload.filter_seen([g], known)], "pattern string")


_need = ", ".join(f"('{k}', '{a}', '{b}')" for k, g in _RANDOM.items() for a, b in _pairs_of(g))
_add("query_filter", "host", _kept_queries, f"SELECT pattern FROM (VALUES {_need}) n(pattern, a, b) LEFT JOIN paths ON sig1 = a AND sig2 = b GROUP BY pattern HAVING count(cnt) = count(*)", sql.PATHS)


def _histogram(rows: DataFrame) -> DataFrame:
    """Queries by whole powers of ten of the relative selectivity, with the strategies that the rule gives them."""
    return rows.filter("log10_xi is not null").groupBy(F.floor("log10_xi").cast("int").alias("power"), "strategy").agg(F.count("*").alias("queries"))


def _social_xi(e: DataFrame) -> DataFrame:
    known = cutting.collect_statistics(e)
    triples = [(r.src_type, r.etype, r.dst_type) for r in workload.valid_triples(e).collect()]
    group = workload.filter_seen([workload.random_typed_path(4, triples, i) for i in range(100)], known)
    return _xi_rows(e, {f"path{i:03}": g for i, g in enumerate(workload.uniform_by_selectivity(group, known, 25))})


_add("xi_study_social", "social", _social_xi, None)
_add("xi_hist_facet", "facet", lambda e: _histogram(_xi_rows(e, workload.facet_diamonds())), None)
_add("xi_hist_community", "community", lambda e: _histogram(_group_xi(e, [f"c{i}" for i in range(7)])), None)
_add("xi_hist_social", "social", lambda e: _histogram(_social_xi(e)), None)

# Stability of two-edge paths, and other statistics.

for _g, _w in (("facet", 50_000), ("host", 2_000)):
    _slots = f"""si AS (SELECT eid // {_w} AS slot, src AS v, 'o:' || etype AS sig FROM edges UNION ALL SELECT eid // {_w}, dst, 'i:' || etype FROM edges),
sc AS (SELECT slot, v, sig, count(*) AS n FROM si GROUP BY ALL),
n AS (SELECT a.slot, a.sig AS s1, b.sig AS s2, CAST(sum(CASE WHEN a.sig = b.sig THEN a.n * (a.n - 1) // 2 ELSE a.n * b.n END) AS BIGINT) AS n FROM sc a JOIN sc b ON a.slot = b.slot AND a.v = b.v AND a.sig <= b.sig GROUP BY 1, 2, 3 HAVING sum(CASE WHEN a.sig = b.sig THEN a.n * (a.n - 1) // 2 ELSE a.n * b.n END) > 0),
f AS (SELECT s.slot, k.s1, k.s2, coalesce(n.n, 0) AS n FROM (SELECT DISTINCT slot FROM n) s CROSS JOIN (SELECT DISTINCT s1, s2 FROM n) k LEFT JOIN n ON n.slot = s.slot AND n.s1 = k.s1 AND n.s2 = k.s2),
r AS (SELECT slot, s1, s2, row_number() OVER (PARTITION BY slot ORDER BY n, s1, s2) AS r FROM f),
b AS (SELECT r.slot, r.s1, r.s2, r.r, p.r AS p FROM r JOIN r p ON p.slot = r.slot - 1 AND p.s1 = r.s1 AND p.s2 = r.s2)"""
    _add(f"stability_pair_{_g}", _g, lambda e, w=_w: stats.order_stability(e, w, "pair"), "SELECT a.slot, count(*) AS pairs, count(*) FILTER ((a.r < b.r) <> (a.p < b.p)) AS inverted FROM b a JOIN b ON a.slot = b.slot AND (a.s1 < b.s1 OR a.s1 = b.s1 AND a.s2 < b.s2) GROUP BY a.slot", _slots)
_add("degree_percentiles", "facet", stats.degree_percentiles, "SELECT sig, round(quantile_cont(n, 0.5), 6) AS p50, round(quantile_cont(n, 0.9), 6) AS p90, round(quantile_cont(n, 0.99), 6) AS p99 FROM (SELECT v, sig, count(*) AS n FROM inc GROUP BY v, sig) GROUP BY sig", sql.INCIDENCE)
_add("triples_cube", "social", lambda e: workload.valid_triples(e, cube=True), f"SELECT CAST(src >> {graphs.BITS} AS INTEGER) AS src_type, etype, CAST(dst >> {graphs.BITS} AS INTEGER) AS dst_type, count(*) AS n FROM edges GROUP BY CUBE (1, 2, 3)")
_add("rarest_kinds", "social", lambda e: stats.edge_histogram(e).orderBy("freq", "etype").limit(5), "SELECT etype, count(*) AS freq FROM edges GROUP BY etype ORDER BY freq, etype LIMIT 5")
_add("vertex_estimate", "social", stats.vertex_estimate, None)
_add("stratified_sample", "social", lambda e: stats.edge_histogram(stats.stratified_sample(e, {"places": 0.5, "in_nation": 1.0})), None)

# Operators around the methods.

_slot = lambda: F.floor(F.col("eid") / 1000).cast("long")
_add("cumulative_edges", "host", lambda e: e.groupBy(_slot().alias("slot"), "etype").agg(F.count("*").alias("n")).withColumn("total", F.sum("n").over(Window.partitionBy("etype").orderBy("slot").rowsBetween(Window.unboundedPreceding, 0))), "SELECT slot, etype, n, CAST(sum(n) OVER (PARTITION BY etype ORDER BY slot ROWS UNBOUNDED PRECEDING) AS BIGINT) AS total FROM (SELECT eid // 1000 AS slot, etype, count(*) AS n FROM edges GROUP BY 1, 2)")
_add("kind_drift", "host", lambda e: e.groupBy(_slot().alias("slot"), "etype").agg(F.count("*").alias("n")).withColumn("change", F.col("n") - F.lag("n").over(Window.partitionBy("etype").orderBy("slot"))), "SELECT slot, etype, n, n - lag(n) OVER (PARTITION BY etype ORDER BY slot) AS change FROM (SELECT eid // 1000 AS slot, etype, count(*) AS n FROM edges GROUP BY 1, 2)")
_add("range_frame", "host", lambda e: e.select("eid", F.count("*").over(Window.partitionBy("src").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-86_400_000_000, 0)).alias("n")), "SELECT eid, count(*) OVER (PARTITION BY src ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS n FROM edges")
_add("win_sliding", "host", lambda e: e.groupBy(F.window("ts", "2 days", "1 day").alias("w"), "etype").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "etype", "n"), "SELECT date_trunc('day', ts) - INTERVAL (k) DAY AS start, etype, count(*) AS n FROM edges, (SELECT unnest(range(2)) AS k) GROUP BY 1, 2")
_add("win_session", "host", lambda e: e.filter("etype in ('k3', 'k4')").groupBy(F.session_window("ts", "6 hours").alias("w"), "etype").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "etype", "n"), "SELECT min(ts) AS start, etype, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY etype ORDER BY ts, eid) AS s FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY etype ORDER BY ts, eid) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM edges WHERE etype IN ('k3', 'k4'))) GROUP BY etype, s")
_add("evolution_daily", "host", lambda e: e.groupBy(F.date_trunc("day", "ts").cast("timestamp_ntz").alias("day"), F.hour("ts").cast("long").alias("hour")).agg(F.count("*").alias("n")), "SELECT date_trunc('day', ts) AS day, hour(ts) AS hour, count(*) AS n FROM edges GROUP BY 1, 2")
_add("snapshot_outer", "social", lambda e: stats.edge_histogram(e.filter("eid < 50000")).withColumnRenamed("freq", "early").join(stats.edge_histogram(e.filter("eid >= 50000")).withColumnRenamed("freq", "late"), "etype", "full"), "SELECT coalesce(a.etype, b.etype) AS etype, early, late FROM (SELECT etype, count(*) AS early FROM edges WHERE eid < 50000 GROUP BY 1) a FULL JOIN (SELECT etype, count(*) AS late FROM edges WHERE eid >= 50000 GROUP BY 1) b ON a.etype = b.etype")


def _lateral(e: DataFrame) -> DataFrame:
    return e.sparkSession.sql("SELECT e.eid, n, latest FROM {e} e, LATERAL (SELECT count(*) AS n, max(p.eid) AS latest FROM {e} p WHERE p.src = e.src AND p.etype = 'k3') WHERE e.etype = 'k4'", e=e)


_add("lateral_neighbours", "host", _lateral, "SELECT e.eid, (SELECT count(*) FROM edges p WHERE p.src = e.src AND p.etype = 'k3') AS n, (SELECT max(p.eid) FROM edges p WHERE p.src = e.src AND p.etype = 'k3') AS latest FROM edges e WHERE etype = 'k4'")
_add("udaf_skew", "facet", lambda e: stats.two_edge_paths(e).groupBy("sig1").agg(F.round(user.gini("cnt"), 6).alias("gini")), "SELECT sig1, round(sum((2 * r - n - 1) * cnt) / (any_value(n) * sum(cnt)), 6) AS gini FROM (SELECT sig1, cnt::DOUBLE AS cnt, row_number() OVER (PARTITION BY sig1 ORDER BY cnt) AS r, count(*) OVER (PARTITION BY sig1) AS n FROM paths) GROUP BY sig1", sql.PATHS)


def _table_function(e: DataFrame) -> DataFrame:
    user.register(e.sparkSession)
    return e.sparkSession.sql("SELECT v, sig, count(*) AS n FROM {e} e, LATERAL incident(e.src, e.dst, e.etype) GROUP BY v, sig", e=e)


_add("udtf_incidence", "host", _table_function, "SELECT v, sig, count(*) AS n FROM inc GROUP BY v, sig", sql.INCIDENCE)

# On the tables themselves.

_Q["udf_kind"] = lambda s, d: graphs.load(s, d, "events").select(user.band_of(graphs.BANDS)("value").alias("etype")).groupBy("etype").agg(F.count("*").alias("freq"))
_SQL["udf_kind"] = f"SELECT {sql._case('value')} AS etype, count(*) AS freq FROM events GROUP BY 1"
_Q["kind_json"] = lambda s, d: graphs.load(s, d, "events").select((F.from_json("props", "k long")["k"] % 3).alias("k"), F.get(F.map_keys(F.from_json("props", "map<string,string>")), 0).alias("key")).groupBy("k", "key").agg(F.count("*").alias("freq"))
_SQL["kind_json"] = "SELECT cast(json_extract_string(props, '$.k') AS BIGINT) % 3 AS k, json_keys(props)[1] AS key, count(*) AS freq FROM events GROUP BY 1, 2"
_Q["page_hosts"] = lambda s, d: graphs.load(s, d, "pages").groupBy(F.lower(F.regexp_extract("url", r"://([^/?#]*)", 1)).alias("host")).agg(F.count("*").alias("n"))
_SQL["page_hosts"] = "SELECT lower(regexp_extract(url, '://([^/?#]*)', 1)) AS host, count(*) AS n FROM pages GROUP BY 1"


def queries() -> dict[str, Query]:
    return dict(_Q)


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)

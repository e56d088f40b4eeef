"""Queries of the engine by name, and the SQL that they are compared with."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphwatch import oracles as sql
from graphwatch.api import watch
from graphwatch.functions.storage import scratch_path, table
from graphwatch.model import ANY, JoinTree, Leaf, QueryEdge, QueryGraph, pattern
from graphwatch.operators import baselines, matching, stats
from graphwatch.operators.delta import advance_all
from graphwatch.plans import cutting, workload
from graphwatch.sources import graphs

Query = Callable[[SparkSession, str], DataFrame]
_Q: dict[str, Query] = {}
_SQL: dict[str, str] = {}

GRAPHS: dict[str, Query] = {
    "facet": graphs.facet_graph,
    "host": graphs.host_graph,
    "community": lambda s, d: graphs.host_graph(s, d, "community"),
    "trade": graphs.trade_graph,
    "social": graphs.social_graph,
}


def _add(name: str, graph: str, query: Callable[[DataFrame], DataFrame], body: str | None, ctes: str = "") -> None:
    _Q[name] = lambda s, d: query(GRAPHS[graph](s, d))
    if body:
        _SQL[name] = sql.over(graph, body, ctes)


def _run(graph: QueryGraph, strategy: str) -> Callable[[DataFrame], DataFrame]:
    def query(edges: DataFrame) -> DataFrame:
        return watch(edges, graph, strategy, prefix=None)

    return query


def _tree(edges: DataFrame, graph: QueryGraph, size: str = "edge", **settings) -> JoinTree:
    return cutting.cut_pattern(graph, cutting.collect_statistics(edges), size, **settings)


# Patterns under every strategy and baseline; one SQL text serves all of a pattern's queries.

PATTERNS: dict[str, tuple[str, QueryGraph]] = {
    "diamond_customer_part": ("facet", workload.facet_diamond("customer", "part")),
    "diamond_part_part": ("facet", workload.facet_diamond("part", "part")),
    "host_path2": ("host", workload.HOST["host_path2"]),
    "host_path3": ("host", workload.HOST["host_path3"]),
    "host_path4": ("host", workload.HOST["host_path4"]),
    "host_tree5": ("host", workload.HOST["host_tree5"]),
    "social_path3": ("social", workload.SOCIAL["social_path3"]),
    "social_path5": ("social", workload.SOCIAL["social_path5"]),
    "social_tree5": ("social", workload.SOCIAL["social_tree5"]),
    "social_act4": ("social", workload.SOCIAL["social_act4"]),
}
STRATEGIES = ("eager1", "gated1", "eager2", "gated2")
for _name, (_g, _p) in PATTERNS.items():
    _body = sql.matches(_p)
    for _s in STRATEGIES:
        _add(f"{_name}__{_s}", _g, _run(_p, _s), _body)
    _add(f"{_name}__flat", _g, lambda e, p=_p: baselines.flat_join(e, p), _body)
for _name in ("host_path3", "social_tree5"):
    _g, _p = PATTERNS[_name]
    _body = sql.matches(_p)
    _add(f"{_name}__delta5", _g, lambda e, p=_p: advance_all(e, _tree(e, p), p, 5, e.count()), _body)
    _add(f"{_name}__delta5_gated", _g, lambda e, p=_p: advance_all(e, _tree(e, p), p, 5, e.count(), gated=True), _body)
    _add(f"{_name}__periodic5", _g, lambda e, p=_p: baselines.rematch_every(e, p, 5, e.count()), _body)


def _ball(edges: DataFrame, graph: QueryGraph) -> DataFrame:
    """The last fifth of the stream as the batch."""
    n = edges.count() * 4 // 5
    return baselines.rematch_neighbourhood(edges.filter(F.col("eid") < n), edges.filter(F.col("eid") >= n), graph)


_P3 = workload.HOST["host_path3"]
_add("host_path3__ball", "host", lambda e: _ball(e, _P3), sql.matches(_P3, "greatest(e0.eid, e1.eid, e2.eid) >= (SELECT count(*) * 4 // 5 FROM edges)"))
for _name, _p in workload.HOST.items():
    if _name not in PATTERNS and _name != "host_path5r":
        _add(f"{_name}__gated1", "host", _run(_p, "gated1"), sql.matches(_p))
for _name, _p in workload.SOCIAL.items():
    if _name not in PATTERNS:
        _add(f"{_name}__gated1", "social", _run(_p, "gated1"), sql.matches(_p))
for _name in ("community_path4", "community_path4m"):
    _add(f"{_name}__auto", "community", _run(workload.COMMUNITY[_name], "auto"), sql.matches(workload.COMMUNITY[_name]))
_add("watch_auto", "facet", _run(workload.facet_diamond("customer", "supplier"), "auto"), sql.matches(workload.facet_diamond("customer", "supplier")))


for _name, _p in workload.facet_diamonds().items():
    # Pieces of two edges: both of an article. Counts without the matches, as some of the results are large; pairs of a facet's articles would be as many as its degree squared.
    _add(f"{_name}__count", "facet", lambda e, p=_p: matching.count_matches(e, JoinTree((Leaf(p.edges[:2]), Leaf(p.edges[2:]))), p), sql.diamond_count(*_name.split("_")[1:]))

# Incomplete and ablated forms.

_P2 = workload.HOST["host_path2"]
_K4K1K0 = pattern("a -k4> b", "b -k1> c", "c -k0> d")
_ENDPOINT_TREE = JoinTree((Leaf(_K4K1K0.edges[:1]), Leaf(_K4K1K0.edges[1:])))
_since = "(SELECT min(g.eid) FROM edges g WHERE g.etype = 'k4' AND g.src <> g.dst AND {v} IN (g.src, g.dst))"
_endpoint = "(greatest(e1.eid, e2.eid) < e0.eid OR e1.eid > e2.eid OR EXISTS (SELECT 1 FROM since s WHERE s.v IN (e2.src, e2.dst) AND s.eid < e2.eid))"
_SINCE = "since AS (SELECT v, min(eid) AS eid FROM (SELECT src AS v, eid FROM edges WHERE etype = 'k4' UNION ALL SELECT dst, eid FROM edges WHERE etype = 'k4') GROUP BY v)"
_add("gated_forward_only", "host", lambda e: matching.run_tree(e, _tree(e, _P2), _P2, gated=True, back=False), sql.matches(_P2, "e1.eid > e0.eid"))
_add("gated_no_look_back", "host", lambda e: matching.without_look_back(e, JoinTree(tuple(Leaf((x,)) for x in _P2.edges)), _P2), sql.matches(_P2, "e1.eid > (SELECT min(s.eid) FROM edges s WHERE s.etype = 'k4' AND s.dst = e0.dst)"))


def _backwards(e: DataFrame) -> DataFrame:
    """The stream from its end, gated, in four batches: the common edges come before the rare ones."""
    n = e.count()
    return advance_all(e.withColumn("eid", n - 1 - F.col("eid")), _tree(e, _P2), _P2, 4, n, gated=True)


_add("gated_arrival_order", "host", _backwards, sql.matches(_P2).replace("FROM edges ", "FROM reversed "), "reversed AS (SELECT (SELECT count(*) FROM edges) - 1 - eid AS eid, src, dst, etype, ts FROM edges)")
_add("gate_endpoint", "host", lambda e: matching.endpoint_gated(e, _ENDPOINT_TREE, _K4K1K0), sql.matches(_K4K1K0, _endpoint), _SINCE)
_add(
    "gate_endpoint_recall", "host",
    lambda e: matching.endpoint_gated(e, _ENDPOINT_TREE, _K4K1K0).agg(F.count("*").alias("found")).join(F.broadcast(matching.run_tree(e, _ENDPOINT_TREE, _K4K1K0).agg(F.count("*").alias("all_matches")))),
    f"SELECT (SELECT count(*) FROM ({sql.matches(_K4K1K0, _endpoint)})) AS found, (SELECT count(*) FROM ({sql.matches(_K4K1K0)})) AS all_matches", _SINCE,
)
_add("gate_vertex", "host", lambda e: matching.run_tree(e, _tree(e, _P3), _P3, gated=True, gate="vertex"), sql.matches(_P3))
_add("within_window", "host", lambda e: watch(e, _P2, "gated1", prefix=None, within="'2' DAY"), sql.matches(_P2, within="'2' DAY"))
for _o in ("dp", "mst", "random", "genetic", "cover"):
    _add(f"order_{_o}", "host", lambda e, o=_o: matching.run_tree(e, _tree(e, _P3, order=o), _P3), sql.matches(_P3))
_add("sql_pattern", "host", lambda e: (e.createOrReplaceTempView("watch_edges"), e.sparkSession.sql(cutting.to_sql(_tree(e, _P3), _P3, "watch_edges")))[1], sql.matches(_P3))

# Pieces, joins, gates.

_E = {"k4": "e_e0", "k0": "e_e1"}
_k4 = pattern("a -k4> b")
_add("piece1_type", "host", lambda e: matching.edge_matches(e, _k4.edges[0]), "SELECT src AS v_a, dst AS v_b, eid AS e_e0 FROM edges WHERE etype = 'k4'")
_add("piece1_label", "host", lambda e: matching.edge_matches(e, _k4.edges[0], pattern("a -k4> b", a="vid < 10")), "SELECT src AS v_a, dst AS v_b, eid AS e_e0 FROM edges WHERE etype = 'k4' AND src < 10")
_REGEX = QueryEdge("e0", "a", "b", ANY, "etype rlike '^(part|nation)$'")
_add("piece1_regex", "facet", lambda e: matching.edge_matches(e, _REGEX), "SELECT src AS v_a, dst AS v_b, eid AS e_e0 FROM edges WHERE regexp_matches(etype, '^(part|nation)$')")
for _form, _pp in {"in-in": pattern("a -k3> c", "b -k2> c"), "out-out": pattern("c -k3> a", "c -k2> b"), "in-out": pattern("a -k3> c", "c -k2> b"), "out-in": pattern("c -k3> a", "b -k2> c")}.items():
    _b = sql.matches(_pp).replace(", greatest(e0.eid, e1.eid) AS last_eid", "")
    _add(f"piece2_{_form.replace('-', '')}", "host", lambda e, f=_form: matching.pair_matches(e, "k3", "k2", f), _b)
_add("triad_closed", "host", lambda e: matching.triad_matches(e, ("k3", "k2", "k1"), True), sql.matches(pattern("a -k3> b", "b -k2> c", "c -k1> a")))
_add("triad_open", "host", lambda e: matching.triad_matches(e, ("k4", "k3", "k2"), False), sql.matches(pattern("a -k4> b", "b -k3> c", "c -k2> d")))


def _two(e: DataFrame) -> tuple[DataFrame, DataFrame]:
    return matching.edge_matches(e, _P2.edges[0]), matching.edge_matches(e, _P2.edges[1])


for _hint in (None, "broadcast", "merge", "shuffle_hash"):
    _add(f"join_bindings_{_hint or 'free'}", "host", lambda e, h=_hint: matching.join_bindings(*_two(e), {"e_e0": "k4", "e_e1": "k0"}, hint=h), sql.matches(_P2).replace(", greatest(e0.eid, e1.eid) AS last_eid", ""))
_add("homomorphism", "host", lambda e: matching.run_tree(e, _tree(e, _P2), _P2, semantics="homomorphism"), "SELECT a.src AS v_a, a.dst AS v_b, b.dst AS v_c, a.eid AS e_e0, b.eid AS e_e1, greatest(a.eid, b.eid) AS last_eid FROM edges a JOIN edges b ON a.dst = b.src WHERE a.etype = 'k4' AND b.etype = 'k0'")
_add("project_cut", "host", lambda e: matching.project_cut(_two(e)[0], ["b"]), "SELECT DISTINCT dst AS v_b FROM edges WHERE etype = 'k4'")
_GATE = "g AS (SELECT v AS vid, 1::INTEGER AS leaf, min(eid) AS since_eid FROM (SELECT src AS v, eid FROM edges WHERE etype = 'k4' UNION ALL SELECT dst, eid FROM edges WHERE etype = 'k4') GROUP BY v)"
_gate = lambda e: matching.gate_rows(_two(e)[0], 1)
_add("gate_rows", "host", _gate, "SELECT * FROM g", _GATE)
_add("gate_mask", "host", lambda e: matching.gate_mask(_gate(e).unionByName(_gate(e).withColumn("leaf", F.lit(3).cast("int")))), "SELECT vid, 10::BIGINT AS mask FROM g", _GATE)
_add("gate_edges_endpoint", "host", lambda e: matching.gate_edges(e.filter("etype = 'k1'"), _gate(e), 1).select("eid"), "SELECT eid FROM edges WHERE etype = 'k1' AND (src IN (SELECT vid FROM g) OR dst IN (SELECT vid FROM g))", _GATE)
_add("gate_edges_cut", "host", lambda e: matching.gate_edges(e.filter("etype = 'k1'"), _gate(e), 1, "src").select("eid"), "SELECT eid FROM edges WHERE etype = 'k1' AND src IN (SELECT vid FROM g)", _GATE)
_add("back_search", "host", lambda e: matching.back_search(e, _gate(e), _P2.edges[1], 1), "SELECT i.eid, g.vid, g.since_eid FROM (SELECT eid, src AS v FROM edges WHERE etype = 'k0' UNION ALL SELECT eid, dst FROM edges WHERE etype = 'k0') i JOIN g ON i.v = g.vid WHERE i.eid < g.since_eid", _GATE)
_add("canonical_subgraphs", "facet", lambda e: matching.canonical_subgraphs(watch(e, workload.facet_diamond("customer", "part"), "gated1", prefix=None)).select(F.array_join("edges", ",").alias("edge_set")), "SELECT DISTINCT array_to_string(list_sort([e_e0, e_e1, e_e2, e_e3]), ',') AS edge_set FROM m", f"m AS ({sql.matches(workload.facet_diamond('customer', 'part'))})")
_add("match_map", "host", lambda e: watch(e, _P2, "gated1", prefix=None).select(F.explode(F.map_from_arrays(F.array(F.lit("a"), F.lit("b"), F.lit("c")), F.array("v_a", "v_b", "v_c"))).alias("vertex", "vid"), "e_e0", "e_e1"), "SELECT vertex, vid, e_e0, e_e1 FROM m, LATERAL (VALUES ('a', v_a), ('b', v_b), ('c', v_c)) t(vertex, vid)", f"m AS ({sql.matches(_P2)})")

# Statistics.

for _g in ("facet", "host", "social", "trade"):
    _add(f"edge_hist_{_g}", _g, stats.edge_histogram, "SELECT etype, count(*) AS freq FROM edges GROUP BY etype")
    _add(f"paths_{_g}", _g, stats.two_edge_paths, "SELECT * FROM paths", sql.PATHS)
    _add(f"graph_size_{_g}", _g, lambda e: e.agg(F.count("*").alias("edges"), F.count_distinct("etype").alias("kinds")).join(F.broadcast(e.select(F.explode(F.array("src", "dst")).alias("v")).agg(F.count_distinct("v").alias("vertices")))), "SELECT count(*) AS edges, count(DISTINCT etype) AS kinds, (SELECT count(DISTINCT v) FROM (SELECT src AS v FROM edges UNION ALL SELECT dst FROM edges)) AS vertices FROM edges")
    _add(f"signatures_{_g}", _g, stats.signature_summary, "SELECT (SELECT count(DISTINCT etype) FROM edges) AS kinds, (SELECT count(*) FROM edges) AS edges, (SELECT count(*) FROM paths) AS signatures, (SELECT CAST(sum(cnt) AS BIGINT) FROM paths) AS total", sql.PATHS)
_add("paths_strict", "host", lambda e: stats.two_edge_paths(e, "strict"), "SELECT * FROM paths", sql.STRICT)
_add("paths_strict_trade", "trade", lambda e: stats.two_edge_paths(e, "strict"), "SELECT * FROM paths", sql.STRICT)
_add("paths_prefix", "social", lambda e: stats.two_edge_paths(stats.sample_prefix(e, 10_000)), "SELECT * FROM paths", sql.PATHS.replace("FROM edges", "FROM edges WHERE eid < 10000"))
_add("paths_same_kind", "facet", lambda e: stats.two_edge_paths(e).filter("sig1 = sig2"), "SELECT * FROM paths WHERE sig1 = sig2", sql.PATHS)
_add("paths_cross_kind", "facet", lambda e: stats.two_edge_paths(e).filter("sig1 < sig2"), "SELECT * FROM paths WHERE sig1 < sig2", sql.PATHS)


def _incremental(e: DataFrame) -> DataFrame:
    counters, n = stats.PathCounters(), e.count()
    for b in range(3):
        counters.update(e.filter((F.col("eid") * 3 >= b * n) & (F.col("eid") * 3 < (b + 1) * n)))
    return counters.paths


_add("paths_incremental", "facet", _incremental, "SELECT * FROM paths", sql.PATHS)
_add("incidence", "host", stats.incidence_counts, "SELECT v, sig, count(*) AS n FROM inc GROUP BY v, sig", sql.INCIDENCE)
_add("mean_degree", "facet", stats.mean_degree, "SELECT sig, CAST(sum(n) AS BIGINT) AS edges, count(*) AS vertices FROM (SELECT v, sig, count(*) AS n FROM inc GROUP BY v, sig) GROUP BY sig", sql.INCIDENCE)
for _g in ("facet", "host", "social"):
    _add(f"selectivity1_{_g}", _g, lambda e: stats.selectivity_distribution(stats.edge_histogram(e), "freq", ["etype"]), "SELECT etype, freq, CAST(sum(freq) OVER () AS BIGINT) AS total, row_number() OVER (ORDER BY freq, etype) AS rank FROM (SELECT etype, count(*) AS freq FROM edges GROUP BY etype)")
    _add(f"selectivity2_{_g}", _g, lambda e: stats.selectivity_distribution(stats.two_edge_paths(e), "cnt", ["sig1", "sig2"]), "SELECT *, CAST(sum(cnt) OVER () AS BIGINT) AS total, row_number() OVER (ORDER BY cnt, sig1, sig2) AS rank FROM paths", sql.PATHS)
for _g, _n in (("facet", 10_000), ("host", 1_000), ("social", 10_000)):
    _add(f"evolution_{_g}", _g, lambda e, n=_n: stats.interval_counts(e, n), f"SELECT eid // {_n} AS slot, etype, count(*) AS n FROM edges GROUP BY 1, 2")
    _stable = f"""n AS (SELECT eid // {_n} AS slot, etype, count(*) AS n FROM edges GROUP BY 1, 2),
f AS (SELECT s.slot, k.etype, coalesce(n.n, 0) AS n FROM (SELECT DISTINCT slot FROM n) s CROSS JOIN (SELECT DISTINCT etype FROM n) k LEFT JOIN n ON n.slot = s.slot AND n.etype = k.etype),
r AS (SELECT slot, etype, row_number() OVER (PARTITION BY slot ORDER BY n, etype) AS r FROM f),
b AS (SELECT r.slot, r.etype, r.r, p.r AS p FROM r JOIN r p ON p.slot = r.slot - 1 AND p.etype = r.etype)"""
    _add(f"stability_{_g}", _g, lambda e, n=_n: stats.order_stability(e, n), "SELECT a.slot, count(*) AS pairs, count(*) FILTER ((a.r < b.r) <> (a.p < b.p)) AS inverted FROM b a JOIN b ON a.slot = b.slot AND a.etype < b.etype GROUP BY a.slot", _stable)
_UND = """und AS (SELECT DISTINCT least(src, dst) AS a, greatest(src, dst) AS b, etype FROM edges WHERE src <> dst)"""
_add("triangles", "host", stats.triangle_counts, "SELECT array_to_string(list_sort([x.etype, y.etype, z.etype]), ',') AS kinds, count(*) AS n FROM und x JOIN und y ON x.b = y.a JOIN und z ON z.a = x.a AND z.b = y.b GROUP BY 1", _UND)
_add("triangle_estimate", "host", lambda e: stats.triangle_estimate(e, 0.5), None)
_add("hub_vertices", "facet", lambda e: graphs.hub_vertices(e, 20), "SELECT v AS vid, count(*) AS degree FROM inc GROUP BY v ORDER BY degree DESC, vid LIMIT 20", sql.INCIDENCE)
_add("drop_hubs", "host", lambda e: graphs.drop_vertices(e, "vid < 20").select("eid"), "SELECT eid FROM edges WHERE src >= 20 AND dst >= 20")
_add("kind_hash", "host", lambda e: stats.edge_histogram(stats.with_kind(e, graphs.hash_kind(["src", "dst"], 5))), None)
_add("kind_composite", "trade", lambda e: stats.edge_histogram(stats.with_kind(e, graphs.composite_kind(["etype", F.year("ts").cast("string")]))), "SELECT etype || '_' || year(ts) AS etype, count(*) AS freq FROM edges GROUP BY 1")
_add("kind_community", "community", stats.edge_histogram, "SELECT etype, count(*) AS freq FROM edges GROUP BY etype")

# Plans and measures. Logarithms are rounded, as both sides add them up in their own order.


def _xi_rows(e: DataFrame, named: dict[str, QueryGraph]) -> DataFrame:
    known, out = cutting.collect_statistics(e), []
    for name, g in named.items():
        c = cutting.choose_strategy(g, known)
        one = cutting.expected_selectivity(cutting.cut_pattern(g, known, "edge"), known)
        out.append((name, None if one is None else round(one, 6), None if c.log10_xi is None else round(c.log10_xi, 6), c.strategy))
    return e.sparkSession.createDataFrame(out, "pattern string, log10_selectivity1 double, log10_xi double, strategy string")


def _expected1(graph: QueryGraph) -> str:
    return " + ".join(f"(SELECT log10(count(*) FILTER (etype = '{x.etype}')::DOUBLE / count(*)) FROM edges)" for x in graph.edges)


_named = {n: p for n, p in workload.HOST.items() if n != "labeled_path"}
_add("strategy_choice_host", "host", lambda e: _xi_rows(e, _named), None)
_add("strategy_choice_community", "community", lambda e: _xi_rows(e, workload.COMMUNITY), None)
_add("strategy_choice_facet", "facet", lambda e: _xi_rows(e, workload.facet_diamonds()), None)
_add("strategy_choice_social", "social", lambda e: _xi_rows(e, workload.SOCIAL), None)
_add("expected_selectivity1", "host", lambda e: _xi_rows(e, {"host_path3": _P3}).select("pattern", "log10_selectivity1"), f"SELECT 'host_path3' AS pattern, round({_expected1(_P3)}, 6) AS log10_selectivity1")
_pair = "(SELECT log10(max(cnt) FILTER (sig1 = '{0}' AND sig2 = '{1}')::DOUBLE / sum(cnt)) FROM paths)"
_add("relative_selectivity", "host", lambda e: _xi_rows(e, {"host_path3": _P3}).select("pattern", "log10_xi"), f"SELECT 'host_path3' AS pattern, round({_pair.format('i:k4', 'o:k0')} + (SELECT log10(count(*) FILTER (etype = 'k1')::DOUBLE / count(*)) FROM edges) - ({_expected1(_P3)}), 6) AS log10_xi", sql.PATHS)


def _group_xi(e: DataFrame, kinds: list[str], n: int = 25) -> DataFrame:
    """A group of random four-edge paths without unseen pairs, spread over their selectivity, with xi."""
    known = cutting.collect_statistics(e)
    group = workload.filter_seen([workload.random_path(4, kinds, i) for i in range(100)], known)
    return _xi_rows(e, {f"path{i:03}": g for i, g in enumerate(workload.uniform_by_selectivity(group, known, n))})


_add("xi_study_community", "community", lambda e: _group_xi(e, [f"c{i}" for i in range(7)]), None)
_add("xi_study_host", "host", lambda e: _group_xi(e, [f"k{i}" for i in range(7)]), None)
_add("valid_triples", "social", workload.valid_triples, f"SELECT CAST(src >> {graphs.BITS} AS INTEGER) AS src_type, etype, CAST(dst >> {graphs.BITS} AS INTEGER) AS dst_type, count(*) AS n FROM edges GROUP BY ALL")
_stored = "SELECT 0::INTEGER AS leaf, count(*) FILTER (etype = 'k4') AS stored FROM edges UNION ALL SELECT 1::INTEGER, count(*) FILTER (etype = 'k0') FROM edges UNION ALL SELECT 2::INTEGER, count(*) FILTER (etype = 'k1') FROM edges"
_P3_TREE = JoinTree(tuple(Leaf((x,)) for x in _P3.edges))
_add("stored_eager", "host", lambda e: matching.stored_rows(e, _P3_TREE, _P3), _stored)
_add("stored_gated", "host", lambda e: matching.stored_rows(e, _P3_TREE, _P3, gated=True), "SELECT 0::INTEGER AS leaf, (SELECT count(*) FROM edges WHERE etype = 'k4') AS stored UNION ALL SELECT 1::INTEGER, count(*) FROM edges WHERE etype = 'k0' AND src IN (SELECT dst FROM edges WHERE etype = 'k4') UNION ALL SELECT 2::INTEGER, count(*) FROM edges WHERE etype = 'k1' AND src IN (SELECT v_c FROM p)", f"p AS ({sql.matches(_P2)})")
_add("detection_eid", "host", lambda e: watch(e, _P3, "gated1", prefix=None).groupBy("last_eid").agg(F.count("*").alias("n")), "SELECT last_eid, count(*) AS n FROM m GROUP BY last_eid", f"m AS ({sql.matches(_P3)})")
_add("probes", "host", lambda e: matching.tree_counters(e, _P3_TREE, _P3).agg(F.sum("probes").cast("long").alias("probes")), f"SELECT count(*) + (SELECT count(*) FROM ({sql.matches(_P2)})) AS probes FROM edges WHERE etype IN ('k4', 'k0', 'k1')")

# Operators around the methods.

_add("setops_union", "host", lambda e: e.filter("etype = 'k4'").select("src").unionByName(e.filter("etype = 'k3'").select("src")).distinct(), "SELECT DISTINCT src FROM edges WHERE etype IN ('k3', 'k4')")
_add("setops_intersect", "host", lambda e: e.filter("etype = 'k4'").select("src").intersect(e.filter("etype = 'k3'").select("src")), "SELECT src FROM edges WHERE etype = 'k4' INTERSECT SELECT src FROM edges WHERE etype = 'k3'")
_add("setops_except", "host", lambda e: e.filter("etype = 'k3'").select("src").subtract(e.filter("etype = 'k4'").select("src")), "SELECT src FROM edges WHERE etype = 'k3' EXCEPT SELECT src FROM edges WHERE etype = 'k4'")
_add("topk_per_kind", "host", lambda e: stats.incidence_counts(e).withColumn("r", F.row_number().over(Window.partitionBy("sig").orderBy(F.desc("n"), "v"))).filter("r <= 3"), "SELECT * FROM (SELECT v, sig, count(*) AS n, row_number() OVER (PARTITION BY sig ORDER BY count(*) DESC, v) AS r FROM inc GROUP BY v, sig) WHERE r <= 3", sql.INCIDENCE)
_add("asof_edge", "host", lambda e: e.withColumn("prior", F.last(F.when(F.col("etype") == "k3", F.col("eid")), ignorenulls=True).over(Window.partitionBy("src").orderBy("eid").rowsBetween(Window.unboundedPreceding, -1))).filter("etype = 'k4'").select("eid", "prior"), "SELECT e.eid, (SELECT max(p.eid) FROM edges p WHERE p.src = e.src AND p.etype = 'k3' AND p.eid < e.eid) AS prior FROM edges e WHERE etype = 'k4'")
_add("evolution_rollup", "facet", lambda e: e.rollup(F.floor(F.col("eid") / 10_000).cast("long").alias("slot"), "etype").agg(F.count("*").alias("n")), "SELECT slot, etype, count(*) AS n FROM (SELECT eid // 10000 AS slot, etype FROM edges) GROUP BY ROLLUP (slot, etype)")
_add("evolution_pivot", "facet", lambda e: e.groupBy(F.floor(F.col("eid") / 10_000).cast("long").alias("slot")).pivot("etype", ["customer", "nation", "part", "supplier"]).count(), "SELECT eid // 10000 AS slot, nullif(count(*) FILTER (etype = 'customer'), 0) AS customer, nullif(count(*) FILTER (etype = 'nation'), 0) AS nation, nullif(count(*) FILTER (etype = 'part'), 0) AS part, nullif(count(*) FILTER (etype = 'supplier'), 0) AS supplier FROM edges GROUP BY 1")
_add("win_tumbling", "host", lambda e: e.groupBy(F.window("ts", "1 day").alias("w"), "etype").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "etype", "n"), "SELECT date_trunc('day', ts) AS start, etype, count(*) AS n FROM edges GROUP BY 1, 2")


def _roundtrip(e: DataFrame) -> DataFrame:
    path = scratch_path(e.sparkSession, "edges-json")
    e.write.json(path)
    return graphs.read_edges(e.sparkSession, path, "json").select("eid", "src", "dst", "etype")


_add("io_roundtrip", "host", _roundtrip, "SELECT eid, src, dst, etype FROM edges")


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _Q["watch_auto"](spark, sf_dir)


def queries() -> dict[str, Query]:
    from graphwatch import catalogue_more

    return _Q | catalogue_more.queries()


def oracle_sql() -> dict[str, str]:
    from graphwatch import catalogue_more

    return _SQL | catalogue_more.oracle_sql()

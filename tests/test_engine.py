"""Matching, cutting and statistics against brute force on small graphs."""

import itertools
import math
import random

import pytest

from graphwatch.api import watch
from graphwatch.model import JoinTree, Leaf, pattern
from graphwatch.functions.state import StateStore
from graphwatch.model import ANY, QueryEdge, QueryGraph, QueryVertex
from graphwatch.operators import baselines, matching, shapes, stats
from graphwatch.operators.delta import AdaptiveMatcher, DeltaMatcher, advance_all
from graphwatch.plans import cutting, workload
from graphwatch.plans.cutting import Statistics

SCHEMA = "eid long, src long, dst long, etype string, ts timestamp_ntz"


def frame(spark, rows):
    from datetime import datetime, timedelta

    return spark.createDataFrame([(*r, datetime(2024, 1, 1) + timedelta(hours=r[0])) for r in rows], SCHEMA)


def random_rows(seed, n=40, vertices=7, kinds="abc"):
    r = random.Random(seed)
    return [(i, r.randrange(vertices), r.randrange(vertices), r.choice(kinds)) for i in range(n)]


def rows_of(df):
    names = sorted(df.columns)
    return sorted(tuple(r[n] for n in names) for r in df.collect())


def brute(rows, graph):
    found = baselines.backtrack(rows, graph)
    return sorted(tuple(m[n] for n in sorted(m)) for m in found)


PATTERNS = [pattern("x -a> y", "y -b> z"), pattern("x -a> y", "y -a> z", "z -c> w"), pattern("x -a> y", "x -b> z", "y -c> w"), pattern("x -a> z", "y -a> z"), pattern("x -a> y", "y -b> z", "z -c> x")]


@pytest.mark.parametrize("i", range(len(PATTERNS)))
def test_strategies_equal_backtracking(spark, i):
    graph, rows = PATTERNS[i], random_rows(i)
    edges = frame(spark, rows)
    known = cutting.collect_statistics(edges)
    want = brute(rows, graph)
    for size, gated in itertools.product(("edge", "pair"), (False, True)):
        tree = cutting.cut_pattern(graph, known, size)
        assert rows_of(matching.run_tree(edges, tree, graph, gated)) == want
    assert rows_of(baselines.flat_join(edges, graph)) == want
    assert rows_of(baselines.backtrack_matches(edges, graph)) == want
    assert rows_of(edges.sparkSession.sql(cutting.to_sql(tree, graph, "{e}"), e=edges)) == want


@pytest.mark.parametrize("gated", [False, True])
def test_batches_report_each_match_once(spark, gated):
    graph, rows = PATTERNS[1], random_rows(5)
    edges = frame(spark, rows)
    for size in ("edge", "pair"):
        tree = cutting.cut_pattern(graph, cutting.collect_statistics(edges), size)
        for batches in (1, 4):
            assert rows_of(advance_all(edges, tree, graph, batches, len(rows), gated)) == brute(rows, graph)


def test_back_search_finds_what_came_before(spark):
    graph = pattern("a -rare> b", "b -x> c")
    tree = JoinTree((Leaf(graph.edges[:1]), Leaf(graph.edges[1:])))
    matcher = DeltaMatcher(tree, graph, gated=True)
    assert matcher.advance(frame(spark, [(0, 2, 3, "x")])).count() == 0
    assert matcher.advance(frame(spark, [(1, 1, 2, "rare")])).count() == 1
    edges = frame(spark, [(0, 2, 3, "x"), (1, 1, 2, "rare")])
    assert matching.run_tree(edges, tree, graph, True).count() == 1
    assert matching.run_tree(edges, tree, graph, True, back=False).count() == 0


def test_endpoint_gate_misses_the_far_edge(spark):
    graph = pattern("a -rare> b", "b -x> c", "c -y> d")
    tree = JoinTree((Leaf(graph.edges[:1]), Leaf(graph.edges[1:])))
    edges = frame(spark, [(0, 1, 2, "rare"), (1, 2, 3, "x"), (2, 3, 4, "y")])
    assert matching.run_tree(edges, tree, graph, True).count() == 1
    assert matching.endpoint_gated(edges, tree, graph).count() == 0


def test_path_counts_equal_pairs(spark):
    rows = random_rows(9)
    edges = frame(spark, rows)
    inc = [(s, "o:" + k, d, i) for i, s, d, k in rows] + [(d, "i:" + k, s, i) for i, s, d, k in rows]
    for mode in ("printed", "strict"):
        want = {}
        for a, b in itertools.combinations(inc, 2):
            if a[0] != b[0] or mode == "strict" and (a[2] == b[2] or a[2] == a[0] or b[2] == b[0]):
                continue
            key = tuple(sorted((a[1], b[1])))
            want[key] = want.get(key, 0) + 1
        assert {(r.sig1, r.sig2): r.cnt for r in stats.two_edge_paths(edges, mode).collect()} == want
    counters = stats.PathCounters()
    for part in (rows[:10], rows[10:30], rows[30:]):
        counters.update(frame(spark, part))
    assert rows_of(counters.paths) == rows_of(stats.two_edge_paths(edges))


def test_leaves_part_the_pattern_and_stay_connected():
    r = random.Random(3)
    for seed in range(30):
        graph = workload.random_binary_tree(r.randint(2, 7), ["a", "b", "c"], seed)
        sigs = [f"{d}:{k}" for d in "io" for k in "abc"]
        known = Statistics({k: r.randint(1, 99) for k in "abc"}, {(x, y): r.randint(1, 999) for x in sigs for y in sigs if x <= y and r.random() < 0.7})
        for size in ("edge", "pair", "mixed"):
            tree = cutting.cut_pattern(graph, known, size)
            assert sorted(e.name for e in tree.edges) == sorted(e.name for e in graph.edges)
            assert all(tree.cut(i) for i in range(1, len(tree.leaves)))


def test_ascending_order_needs_least_space():
    freqs = [1, 5, 20, 100]
    assert cutting.tree_space(freqs) == min(cutting.tree_space(list(p)) for p in itertools.permutations(freqs))


def test_choice_at_the_threshold():
    graph = pattern("x -a> y", "y -b> z")
    sig = ("i:a", "o:b")
    for pairs, want in ((9, "gated2"), (10, "gated1")):
        known = Statistics({"a": 10, "b": 10}, {sig: pairs, ("o:a", "o:a"): 40_000 - pairs})
        assert cutting.choose_strategy(graph, known).strategy == want
    assert cutting.choose_strategy(graph, Statistics({"a": 1, "b": 1})).tree.fallback is False
    assert cutting.cut_pattern(graph, Statistics({"a": 1, "b": 1}), "pair").fallback


def test_plan_text_round_trip(tmp_path):
    graph = pattern("x -a> y", "y -b> z", x="vid < 3")
    tree = cutting.cut_pattern(graph, Statistics({"a": 1, "b": 2}))
    cutting.save_plan(tree, graph, str(tmp_path / "plan.json"))
    again, same = cutting.load_plan(str(tmp_path / "plan.json"))
    assert again.leaves == tree.leaves and same == graph


def test_edge_cases(spark):
    graph = pattern("x -a> y", "y -b> z")
    empty = frame(spark, [])
    tree = cutting.cut_pattern(graph, cutting.collect_statistics(empty))
    assert matching.run_tree(empty, tree, graph, True).count() == 0
    loops = frame(spark, [(0, 1, 1, "a"), (1, 1, 2, "b")])
    assert matching.run_tree(loops, tree, graph).count() == 0
    with pytest.raises(ValueError):
        cutting.cut_pattern(pattern("x -a> y", "u -b> w"), Statistics({}))


def test_stream_equals_batch(spark, tmp_path):
    from graphwatch.streaming.watch import watch_joins

    graph, rows = PATTERNS[0], random_rows(2)
    edges = frame(spark, rows)
    from pyspark.sql import functions as F

    edges.withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.parquet(str(tmp_path / "in"))
    source = spark.readStream.schema("eid long, src long, dst long, etype string, ts timestamp").parquet(str(tmp_path / "in"))
    tree = JoinTree(tuple(Leaf((e,)) for e in graph.edges))
    query = watch_joins(source, tree, graph).writeStream.format("memory").queryName("found").option("checkpointLocation", str(tmp_path / "c")).start()
    try:
        query.processAllAvailable()
        assert rows_of(spark.table("found")) == brute(rows, graph)
    finally:
        query.stop()


def test_counts_reach_past_every_window(spark, monkeypatch):
    from graphwatch import catalogue

    r = random.Random(8)
    facets = ["part", "supplier", "customer", "nation"]
    # No edge is in the first 20,000 (or 5,000, or 3,000) of its stream.
    rows = [(30_000 + i, a, 100 * k + f, facets[k]) for i, (a, k, f) in enumerate(sorted({(r.randrange(6), r.randrange(4), 10 + r.randrange(3)) for _ in range(60)}))]
    monkeypatch.setitem(catalogue.GRAPHS, "facet", lambda s, d: frame(spark, rows))
    found = catalogue.queries()
    for name, graph in workload.facet_diamonds().items():
        assert found[f"{name}__count"](spark, "").first().n == len(brute(rows, graph)) > 0
    hosts = [(30_000 + i, s, d, k) for i, s, d, k in random_rows(11)]
    monkeypatch.setitem(catalogue.GRAPHS, "host", lambda s, d: frame(spark, hosts))
    monkeypatch.setitem(catalogue.GRAPHS, "trade", lambda s, d: frame(spark, hosts))
    plain = sorted({(min(s, d), max(s, d), k) for _, s, d, k in hosts if s != d})
    want = {}
    for three in itertools.combinations(plain, 3):
        if len({x[:2] for x in three}) == 3 and len({v for x in three for v in x[:2]}) == 3:
            kinds = ",".join(sorted(x[2] for x in three))
            want[kinds] = want.get(kinds, 0) + 1
    assert {x.kinds: x.n for x in found["triangles"](spark, "").collect()} == want
    inc = [(s, "o:" + k, d) for _, s, d, k in hosts if s != d] + [(d, "i:" + k, s) for _, s, d, k in hosts if s != d]
    pairs = {}
    for a, b in itertools.combinations(inc, 2):
        if a[0] == b[0] and a[2] != b[2]:
            key = tuple(sorted((a[1], b[1])))
            pairs[key] = pairs.get(key, 0) + 1
    assert {(x.sig1, x.sig2): x.cnt for x in found["paths_strict_trade"](spark, "").collect()} == pairs


def test_example_trace(spark):
    """Three edges one by one around the middle person; the match comes with the third."""
    graph = pattern("p -knows> q", "q -likes> a", "q -follows> r")
    tree = JoinTree(tuple(Leaf((e,)) for e in graph.edges))
    for gated in (False, True):
        matcher = DeltaMatcher(tree, graph, gated)
        counts = [matcher.advance(frame(spark, [row])).count() for row in [(0, 1, 2, "knows"), (1, 2, 100, "likes"), (2, 2, 3, "follows")]]
        assert counts == [0, 0, 1]
        got = matcher.snapshot().first()
        assert (got.v_p, got.v_q, got.v_a, got.v_r, got.last_eid) == (1, 2, 100, 3, 2)


def test_state_survives_restart_and_replay(spark, tmp_path):
    graph, rows = PATTERNS[1], random_rows(5, 40)
    edges, want = frame(spark, rows), brute(rows, PATTERNS[1])
    tree = cutting.cut_pattern(graph, cutting.collect_statistics(edges), "pair")
    part = lambda b: frame(spark, rows[b * 10 : b * 10 + 10])
    for gated in (False, True):
        path, out = str(tmp_path / f"state{gated}"), []
        for b in range(4):
            # A new matcher for each batch: all that it knows is in the folder. fanout 2: parts are merged on the way.
            matcher = DeltaMatcher(tree, graph, gated, path=path, fanout=2)
            got = rows_of(matcher.advance(part(b), b))
            again = DeltaMatcher(tree, graph, gated, path=path, fanout=2)
            assert rows_of(again.advance(part(b), b)) == got
            out += got
        assert sorted(out) == want == rows_of(matcher.snapshot())
        assert len(StateStore(spark, path).parts["edges"]) < 3
        with pytest.raises(ValueError):
            DeltaMatcher(tree, graph, gated, path=path).advance(part(2), 2)
    # A batch that died before its commit is done again from the state before it.
    path = str(tmp_path / "died")
    first = DeltaMatcher(tree, graph, True, path=path)
    first.advance(part(0), 0)
    store = first._open(spark)
    store.commit, real = lambda number: (_ for _ in ()).throw(RuntimeError("lost")), store.commit
    with pytest.raises(RuntimeError):
        first.advance(part(1), 1)
    later = DeltaMatcher(tree, graph, True, path=path)
    for b in range(1, 4):
        later.advance(part(b), b)
    assert rows_of(later.snapshot()) == want


def test_old_state_is_dropped_within_a_window(spark):
    graph, rows = PATTERNS[0], random_rows(7, 80)
    edges = frame(spark, rows)
    tree = JoinTree(tuple(Leaf((e,)) for e in graph.edges))
    want = sorted(m for m in brute(rows, graph) if abs(m[sorted(["e_e0", "e_e1", "last_eid", "v_x", "v_y", "v_z"]).index("e_e0")] - m[1]) <= 10)
    assert rows_of(matching.run_tree(edges, tree, graph, True, within="'10' HOUR")) == want  # one edge an hour
    for gated in (False, True):
        matcher = DeltaMatcher(tree, graph, gated, within="'10' HOUR", fanout=2)
        for b in range(5):
            matcher.advance(frame(spark, rows[b * 16 : b * 16 + 16]))
        assert rows_of(matcher.snapshot()) == want
        assert matcher.stored()["edges"] < sum(r[3] in "ab" for r in rows)


def test_plans_change_on_the_way(spark):
    graph = pattern("x -a> y", "y -b> z")
    rows = [(i, i % 5, 5 + i % 4, "a") for i in range(4)] + [(4 + i, 5 + i % 4, 9 + i % 3, "b") for i in range(30)]
    tree = JoinTree((Leaf(graph.edges[1:]), Leaf(graph.edges[:1])))
    recut = lambda e: cutting.cut_pattern(graph, cutting.collect_statistics(e)) if cutting.order_changed(tree, cutting.collect_statistics(e)) else None
    matcher = AdaptiveMatcher(tree, graph, recut, every=1)
    out = []
    for b in range(4):
        out += rows_of(matcher.advance(frame(spark, rows[b * 9 : b * 9 + 9])))
    assert matcher.migrations == 1 and matcher.matcher.tree.leaves[0].edges[0].etype == "a"
    assert sorted(out) == rows_of(matcher.snapshot()) == brute(rows, graph)


def test_other_shapes_and_orders(spark):
    graph, rows = pattern("x -a> y", "y -b> z", "z -c> w", "w -a> u"), random_rows(4, 60, 8)
    edges, want = frame(spark, rows), brute(rows, pattern("x -a> y", "y -b> z", "z -c> w", "w -a> u"))
    known = cutting.collect_statistics(edges)
    for order in ("greedy", "dp", "mst", "random", "genetic", "cover"):
        tree = cutting.cut_pattern(graph, known, order=order)
        assert all(tree.cut(i) for i in range(1, 4))
        assert rows_of(shapes.run_bushy(edges, tree, graph)) == want == rows_of(shapes.run_n_ary(edges, tree, graph))
    space = lambda o: cutting.tree_space([known.frequency(x) for x in cutting.cut_pattern(graph, known, order=o).leaves])
    assert space("dp") <= min(space(o) for o in ("greedy", "mst", "genetic", "cover", "random")) and space("genetic") == space("dp")


def test_searches_after_each_edge(spark):
    graph, rows = PATTERNS[0], random_rows(3)
    edges = frame(spark, rows)
    got = baselines.rematch_per_edge(edges, graph)
    assert rows_of(got.drop("reported", "found")) == brute(rows, graph)
    assert all(r.reported == r.last_eid for r in got.collect())
    assert max(r.found for r in got.collect()) == len(brute(rows, graph))
    assert rows_of(baselines.indexed_rematch(edges, graph, 2, len(rows))) == brute(rows, graph)
    counted = baselines.rematch_every(edges, graph, 4, len(rows), counted=True).orderBy("batch").collect()
    assert [r.found for r in counted][:-1] == [r.redundant for r in counted][1:] and counted[-1].found == len(brute(rows, graph))


def test_predicates_bind_the_vertex_only(spark):
    """Names and text that contain vid are left alone."""
    graph = pattern("x -a> y", "y -vid> z", x="vid < 4 AND 'vid' <> 'src'", z="vid <> 2")
    rows = [(i, s, d, "vid" if k == "b" else k) for i, s, d, k in random_rows(6)]
    edges = frame(spark, rows)
    want = sorted(m for m in brute(rows, pattern("x -a> y", "y -vid> z")) if m[3] < 4 and m[5] != 2)
    tree = JoinTree(tuple(Leaf((e,)) for e in graph.edges))
    assert rows_of(matching.run_tree(edges, tree, graph)) == want
    assert rows_of(spark.sql(cutting.to_sql(tree, graph, "{e}"), e=edges)) == want
    from graphwatch.sources.graphs import drop_vertices

    assert {r.eid for r in drop_vertices(edges, "vid = 3 AND 'vid' = 'vid'").collect()} == {r[0] for r in rows if 3 not in r[1:3]}


def test_any_kind_and_labels_of_vertices(spark):
    rows = random_rows(10)
    edges = frame(spark, rows)
    graph = QueryGraph((QueryEdge("e0", "x", "y", ANY, "etype rlike '^[ab]$'"), QueryEdge("e1", "y", "z", "b")), (QueryVertex("y", "person", label="^J"),))
    vertices = spark.createDataFrame([(v, "person" if v % 2 else "place", "Jo" if v < 4 else "Al") for v in range(7)], "vid long, vtype string, label string")
    tree = JoinTree(tuple(Leaf((e,)) for e in graph.edges))
    got = {(r.e_e0, r.e_e1) for r in matching.run_tree(edges, tree, graph, True, vertices=vertices).collect()}
    want = {(a[0], b[0]) for a in rows for b in rows if a[3] in "ab" and b[3] == "b" and a[2] == b[1] and a[0] != b[0] and len({a[1], a[2], b[2]}) == 3 and a[2] in (1, 3)}
    assert got == want
    with pytest.raises(ValueError):
        matching.run_tree(edges, tree, graph)


def test_counters_and_measures(spark):
    graph, rows = PATTERNS[0], random_rows(1)
    edges = frame(spark, rows)
    n = {k: sum(r[3] == k and r[1] != r[2] for r in rows) for k in "ab"}
    pair = JoinTree((Leaf(graph.edges),))
    one = matching.tree_counters(edges, pair, graph).first()
    assert one.searches == n["a"] + n["b"] and one.stored == len(brute(rows, graph)) <= one.neighbours
    tree = JoinTree(tuple(Leaf((e,)) for e in graph.edges))
    eager, gated = (matching.tree_counters(edges, tree, graph, g).orderBy("leaf").collect() for g in (False, True))
    ends = {r[2] for r in rows if r[3] == "a" and r[1] != r[2]}
    assert eager[1].searches == n["b"] and gated[1].searches == sum(r[3] == "b" and r[1] != r[2] and r[1] in ends for r in rows)
    assert eager[1].results == gated[1].results == len(brute(rows, graph)) and eager[1].probes == n["a"] + n["b"]
    assert cutting.q_error(2, 8) == cutting.q_error(8, 2) == 4 and cutting.q_error(0, 0) == 1
    assert cutting.join_cost(3, 5) == (8, 3) and cutting.node_work(1, 2, 3, 5, 10) == 1.4
    known = Statistics({"a": 4, "b": 6}, {("i:a", "o:b"): 7})
    assert cutting.search_cost(Leaf(graph.edges), {"o:b": 2.5}) == 2.5 and cutting.search_cost(tree.leaves[0], {}) == 1
    # 4 + 6 searches, 4 + 6 probes, 4 results over 10 edges.
    assert math.isclose(cutting.tree_work(tree, known, {}), 2.4)
    assert cutting.rarest_piece(graph, known).edges[0].etype == "a"
    assert cutting.should_split(100, [30], 2.0, 3) and not cutting.should_split(100, [30], 2.0, 3, "reversed")
    assert cutting.explain_tree(tree, known) == "0: x -a> y freq=4\n1: y -b> z at y freq=6"


def test_statistics_of_intervals_and_samples(spark):
    rows = random_rows(13, 60)
    edges = frame(spark, rows)
    by = {}
    for a, b in itertools.combinations([(i // 20, s, "o:" + k) for i, s, d, k in rows] + [(i // 20, d, "i:" + k) for i, s, d, k in rows], 2):
        if a[:2] == b[:2]:
            key = (a[0], *sorted((a[2], b[2])))
            by[key] = by.get(key, 0) + 1
    assert {tuple(r)[:3]: r.cnt for r in stats.interval_paths(edges, 20).collect()} == by
    things = sorted({k[1:] for k in by})
    order = [sorted(things, key=lambda t: (by.get((slot, *t), 0), t)) for slot in range(3)]
    want = {slot: sum((order[slot].index(x) < order[slot].index(y)) != (order[slot - 1].index(x) < order[slot - 1].index(y)) for x, y in itertools.combinations(things, 2)) for slot in (1, 2)}
    assert {r.slot: r.inverted for r in stats.order_stability(edges, 20, "pair").collect()} == want
    big = frame(spark, [(i, i % 40, (i * 7 + 1) % 40, "abc"[i % 3]) for i in range(3000)])
    exact = sum(r.n for r in stats.triangle_counts(big).collect())
    whole = sum(r.estimate for r in stats.triangle_estimate(big, 1.0).collect())
    assert whole == exact
    dense = frame(spark, [(i, s, d, "a") for i, (s, d) in enumerate(itertools.combinations(range(40), 2))])
    guess = sum(r.estimate for r in stats.triangle_estimate(dense, 0.5).collect())
    assert abs(guess - 9880) < 0.25 * 9880
    sampled = stats.stratified_sample(big, {"a": 1.0, "b": 0.5})
    counts = {r.etype: r.freq for r in stats.edge_histogram(sampled).collect()}
    assert counts["a"] == 1000 and 400 < counts["b"] < 600 and "c" not in counts
    size = stats.vertex_estimate(big).first()
    assert size.vertices == 40 and abs(size.estimate - 40) <= 2
    from graphwatch.sources.graphs import hash_kind

    kinds = stats.edge_histogram(stats.with_kind(big, hash_kind(["src", "dst"], 5))).collect()
    assert sum(r.freq for r in kinds) == 3000 and {r.etype for r in kinds} <= {f"h{i}" for i in range(5)}


def test_random_groups():
    known = Statistics({"a": 5, "b": 50, "c": 500}, {(x, y): 10 for x in ("i:a", "i:b", "o:a", "o:b") for y in ("i:a", "i:b", "o:a", "o:b") if x <= y})
    group = [workload.random_path(3, ["a", "b", "c"], i) for i in range(60)]
    kept = workload.filter_seen(group, known)
    assert kept and all(e.etype != "c" for g in kept for e in g.edges) and len(kept) == sum(all(e.etype != "c" for e in g.edges) for g in group)
    some = workload.uniform_by_selectivity(kept, known, 4)
    assert len(some) == min(4, len(kept)) and all(g in kept for g in some)
    triples = [(1, "p", 2), (2, "q", 3), (2, "r", 1)]
    for i in range(20):
        for path in (True, False):
            g = workload.random_typed_tree(5, triples, i, path)
            assert len(g.edges) == 5 and g.connected() and len(g.vertex_names) == 6
            degrees = [sum(v in e.ends for e in g.edges) for v in g.vertex_names]
            assert not path or max(degrees) == 2


def streamed(spark, tmp_path, rows, name, build, per=10, **options):
    """The rows, one file for each micro-batch and written in order, through build(source); what the memory table holds."""
    import time

    from pyspark.sql import functions as F

    folder = tmp_path / f"{name}-in"
    for b in range(0, len(rows), per):
        frame(spark, rows[b : b + per]).withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.mode("append").parquet(str(folder))
        time.sleep(0.02)
    source = spark.readStream.schema("eid long, src long, dst long, etype string, ts timestamp").option("maxFilesPerTrigger", 1).parquet(str(folder))
    query = build(source).writeStream.format("memory").queryName(name).outputMode(options.get("mode", "append")).option("checkpointLocation", str(tmp_path / f"{name}-c")).start()
    try:
        query.processAllAvailable()
        return spark.table(name).collect()
    finally:
        query.stop()


def test_state_of_our_own_on_a_stream(spark, tmp_path):
    from graphwatch.streaming.watch import first_seen, watch_joins, watch_pairs

    rows = random_rows(15, 60)
    want = {(m["e_e0"], m["e_e1"], m["v_x"], m["v_y"], m["v_z"]) for m in baselines.backtrack(rows, PATTERNS[0])}
    got = streamed(spark, tmp_path, rows, "pairs", lambda s: watch_pairs(s, "a", "b"), 20)
    assert len(got) == len(want) and {tuple(r) for r in got} == want
    tree = JoinTree(tuple(Leaf((e,)) for e in PATTERNS[0].edges))
    near = streamed(spark, tmp_path, rows, "near", lambda s: watch_joins(s, tree, PATTERNS[0], within="'5' HOUR"), 30)
    assert {(r.e_e0, r.e_e1) for r in near} == {m[:2] for m in want if abs(m[0] - m[1]) <= 5}
    twice = streamed(spark, tmp_path, [r for r in rows for _ in (0, 1)], "twice", lambda s: first_seen(s, "1 day"), 60)
    assert sorted(r.eid for r in twice) == list(range(60))


def test_late_edges_are_dropped_below_the_watermark(spark, tmp_path):
    from graphwatch.streaming.watch import live_histogram

    # Hours 0 to 9, then 40, then one of hour 1: too late for a watermark of 5 hours.
    rows = [(i, 1, 2, "a") for i in range(10)] + [(40, 1, 2, "a"), (41, 1, 2, "a")]
    late = rows + [(1, 1, 2, "a"), (80, 1, 2, "a"), (81, 1, 2, "a")]
    count = lambda name, mark: sum(r.n for r in streamed(spark, tmp_path, late, name, lambda s: live_histogram(s, "2 hours", watermark=mark), 2) if r.window.start.hour in (0,) and r.window.start.day == 1)
    assert count("narrow", "5 hours") == 2 and count("wide", "70 hours") in (0, 3)
    session = streamed(spark, tmp_path, rows + [(90, 1, 2, "a"), (91, 1, 2, "a")], "sessions", lambda s: live_histogram(s, "3 hours", watermark="1 hour", session=True), 2)
    assert sorted(r.n for r in session) == [2, 10]
    sliding = streamed(spark, tmp_path, rows + [(90, 1, 2, "a"), (91, 1, 2, "a")], "sliding", lambda s: live_histogram(s, "4 hours", "2 hours", watermark="1 hour"), 2)
    assert sum(r.n for r in sliding if r.window.end.day == 1 and r.window.end.hour <= 14) >= 18


def test_stream_goes_on_after_a_restart(spark, tmp_path):
    from pyspark.sql import functions as F

    from graphwatch.streaming.watch import watch_batches

    rows, out, seen = random_rows(16, 60), [], []
    tree = JoinTree(tuple(Leaf((e,)) for e in PATTERNS[0].edges))
    source = lambda: spark.readStream.schema("eid long, src long, dst long, etype string, ts timestamp").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "feed"))
    for part in (rows[:20], rows[20:40], rows[40:]):
        frame(spark, part).withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.mode("append").parquet(str(tmp_path / "feed"))
        query = watch_batches(source(), tree, PATTERNS[0], lambda df, n: (out.extend(rows_of(df)), seen.append(n)), str(tmp_path / "checkpoint"))
        query.processAllAvailable()
        query.stop()
    assert sorted(out) == brute(rows, PATTERNS[0]) and seen == [0, 1, 2]


def test_command_line(spark, tmp_path, capsys):
    from graphwatch.__main__ import main

    rows = random_rows(17)
    frame(spark, rows).write.parquet(str(tmp_path / "edges"))
    assert main(["plan", str(tmp_path / "edges"), "x -a> y; y -b> z", str(tmp_path / "plan.json")]) == 0
    assert "gated" in capsys.readouterr().out
    assert main(["run", str(tmp_path / "edges"), str(tmp_path / "plan.json"), str(tmp_path / "out")]) == 0
    got = spark.read.parquet(str(tmp_path / "out"))
    assert got.count() == len(brute(rows, PATTERNS[0]))


def test_graphs_follow_their_folder(spark, tmp_path):
    from graphwatch.sources import graphs

    made = lambda n: spark.createDataFrame([(i, i % 5, f'{{"k":{i % 7}}}', float(i), "e") for i in range(n)], "event_id long, user_id long, props string, value double, event_type string").selectExpr("*", "timestamp_ntz'2024-01-01' ts")
    made(50).write.parquet(str(tmp_path / "events.parquet"))
    before = graphs.host_graph(spark, str(tmp_path)).count()
    assert graphs.host_graph(spark, str(tmp_path)).count() == before
    import shutil

    shutil.rmtree(tmp_path / "events.parquet")
    made(90).write.parquet(str(tmp_path / "events.parquet"))
    assert graphs.host_graph(spark, str(tmp_path)).count() > before


@pytest.mark.parametrize("name", ["back_search", "bushy_host_path4", "cartesian_small", "community_path4m__auto", "counters_eager1", "counters_eager2", "counters_gated1", "counters_gated2", "cumulative_edges", "detection_eid", "diamond_customer_customer__count", "diamond_customer_part__eager1"])
def test_each_query_reads_its_tables(spark, tmp_path, name):
    """A second run in one session scans the tables again: what another query made is not its input."""
    from datetime import datetime, timedelta

    from graphwatch import catalogue

    when = lambda i: datetime(2024, 1, 1) + timedelta(hours=i)
    tables = {
        "events": ([(i, i % 9, f'{{"k":{i % 7}}}', 61.0 * (i % 7), "e", when(i)) for i in range(60)], "event_id long, user_id long, props string, value double, event_type string, ts timestamp_ntz"),
        "orders": ([(i, i % 3, when(i)) for i in range(12)], "o_orderkey long, o_custkey long, o_orderdate timestamp_ntz"),
        "lineitem": ([(i % 12, i % 5, i % 4) for i in range(30)], "l_orderkey long, l_partkey long, l_suppkey long"),
        "customer": ([(i, i % 2) for i in range(3)], "c_custkey long, c_nationkey int"),
    }
    for table, (rows, schema) in tables.items():
        spark.createDataFrame(rows, schema).write.parquet(str(tmp_path / f"{table}.parquet"))

    def records():
        each = spark._jsc.sc().statusStore().stageList(None, False, False, spark.sparkContext._gateway.new_array(spark._jvm.double, 0), spark._jvm.java.util.ArrayList())
        return {each.apply(i).stageId(): each.apply(i).inputRecords() for i in range(each.size())}

    query, read = catalogue.queries()[name], []
    for _ in range(2):
        before = records()
        query(spark, str(tmp_path)).collect()
        read.append(sum(n for k, n in records().items() if k not in before))
    assert read[0] == read[1] >= (30 if name.startswith("diamond") else 60)


def test_a_stored_graph_goes_with_its_query(spark, tmp_path):
    from graphwatch.functions import storage
    from pathlib import Path

    def path():
        return Path(storage._PASSING[-1][2].removeprefix("file:"))

    one = storage.passing_table(spark.range(9), "one")
    first, kept = path(), one.filter("id > 3")
    two = storage.passing_table(spark.range(5), "two")
    second = path()
    del one, two
    for _ in range(20):
        storage.passing_table(spark.range(5), "three")
        if not second.exists():
            break
    assert first.exists() and not second.exists() and kept.count() == 5


def test_counts_do_not_list_the_pairs_of_a_hub(spark):
    """6,000 articles of one nation: 36 million pairs of articles, and no match. Pieces of other shapes are counted like listed ones."""
    from graphwatch.operators.matching import count_matches, run_tree

    one = pattern("a -n> x", "a -n> y", "b -n> x", "b -n> y")
    tree = JoinTree((Leaf(one.edges[:2]), Leaf(one.edges[2:])))
    hub = spark.range(6000).selectExpr("id eid", "id + 10 src", "1L dst", "'n' etype", "timestamp_ntz'2024-01-01' ts")
    before = spark._jsc.sc().statusStore().executorList(False).apply(0).totalShuffleWrite()
    assert count_matches(hub, tree, one).first().n == 0
    assert spark._jsc.sc().statusStore().executorList(False).apply(0).totalShuffleWrite() - before < 1_000_000
    for seed, text in enumerate((("a -a> x", "a -b> y", "b -a> x", "b -b> y"), ("a -a> x", "y -b> a", "x -c> b", "b -a> y"), ("a -a> x", "a -a> y", "b -a> x", "b -a> y"))):
        graph, edges = pattern(*text), frame(spark, random_rows(seed, 60))
        tree = JoinTree((Leaf(graph.edges[:2]), Leaf(graph.edges[2:])))
        assert count_matches(edges, tree, graph).first().n == run_tree(edges, tree, graph).count() > 0


def test_searches_after_each_edge_do_not_grow_with_the_stream(spark):
    """Some 20,000 edges, each followed by a search; a pattern with a kind twice and a cycle; found is what a full search finds then."""
    import time

    rows = random_rows(5, 20_000, 3_000, "abcd")
    began, graph = time.time(), PATTERNS[1]
    got = baselines.rematch_per_edge(frame(spark, rows), graph)
    assert rows_of(got.drop("reported", "found")) == brute(rows, graph) and time.time() - began < 120
    for graph in (PATTERNS[1], PATTERNS[4]):
        rows = random_rows(6, 80)
        for r in baselines.rematch_per_edge(frame(spark, rows), graph).collect():
            assert r.found == len(brute(rows[: r.reported + 1], graph)) and r.reported == r.last_eid


def test_periodic_search_broadcasts_no_earlier_result(spark):
    graph, rows = PATTERNS[1], random_rows(7, 80)
    got = baselines.rematch_every(frame(spark, rows), graph, 4, len(rows))
    assert rows_of(got) == brute(rows, graph) != []
    assert "Join" not in got._jdf.queryExecution().optimizedPlan().toString()


def listed(spark, find):
    """400 articles with one part in common and one of their own; two share a further one. The matches, and the bytes that were shuffled for them, without broadcasts."""
    edges = spark.range(800).selectExpr("id eid", "id div 2 + 10 src", "if(id % 2 = 0, 1L, if(id < 4, 2L, id + 5000)) dst", "'part' etype", "timestamp_ntz'2024-01-01' ts")
    written = lambda: spark._jsc.sc().statusStore().executorList(False).apply(0).totalShuffleWrite()
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        before = written()
        return {(r.v_a, r.v_x, r.v_b, r.v_y) for r in find(edges).collect()}, written() - before
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


DIAMOND = workload.facet_diamond("part", "part")
DIAMONDS = {(a, x, 21 - a, 3 - x) for a in (10, 11) for x in (1, 2)}


FORMS = {"eager1": lambda e: watch(e, DIAMOND, "eager1", prefix=None), "gated1": lambda e: watch(e, DIAMOND, "gated1", prefix=None), "flat": lambda e: baselines.flat_join(e, DIAMOND)}


@pytest.mark.parametrize("form", FORMS)
def test_partial_matches_that_nothing_closes_are_not_shuffled(spark, form):
    """160,000 partial matches of three edges, of which four are completed."""
    found, bytes_ = listed(spark, FORMS[form])
    assert found == DIAMONDS and bytes_ < 300_000


@pytest.mark.parametrize("most", [1, 3, 256])
def test_look_ahead_loses_no_match(spark, monkeypatch, most):
    """Parallel edges, vertices with too many closing edges for a list, slices, cycles of two to four, homomorphisms and time bounds."""
    monkeypatch.setattr(matching, "MOST_ENDS", most)
    monkeypatch.setattr(matching, "SLICE_EDGES", 10 if most == 3 else 10_000)
    for seed, graph in enumerate((DIAMOND, workload.facet_diamond("a", "b"), pattern("x -a> y", "z -b> y", "z -a> x"), pattern("x -a> y", "y -a> z", "y -b> z"))):
        rows = random_rows(seed, 70, 9, "ab") if seed else [(e, s, d, "part") for e, s, d, _ in random_rows(9, 40, 9)]
        tree = JoinTree(tuple(Leaf((e,)) for e in graph.edges))
        assert matching.closing_edge(tree, len(graph.edges) - 2)
        edges, want = frame(spark, rows), brute(rows, graph)
        for gated, gate in ((False, "role"), (True, "role"), (True, "vertex")):
            assert rows_of(matching.run_tree(edges, tree, graph, gated, gate)) == want != []
        if most == 3:
            settings = ({"semantics": "homomorphism"}, {"within": "'20' HOUR"}, {"back": False})
            got = [rows_of(matching.run_tree(edges, tree, graph, **s)) for s in settings]
            with monkeypatch.context() as plain:
                plain.setattr(matching, "closing_edge", lambda *_: None)
                assert got == [rows_of(matching.run_tree(edges, tree, graph, **s)) for s in settings]

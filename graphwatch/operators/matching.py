"""Matches of pieces and of whole patterns, as tables of v_* and e_* columns."""

from __future__ import annotations

import itertools
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphwatch.functions.storage import cut, passing_table
from graphwatch.model import ANY, JoinTree, Leaf, QueryEdge, QueryGraph

#: A vertex with more closing edges than this has no list of their other ends (look_ahead), so no row grows beyond a fixed size.
MOST_ENDS = 256
#: A join that looks ahead is done in slices, one after the other: one for so many closing edges, up to that many, as each slice reads all of them.
SLICE_EDGES, MOST_SLICES = 10_000_000, 4


def at_vertex(rows: DataFrame, predicate: str, column: str) -> DataFrame:
    """The rows whose vertex in ``column`` fits a predicate over vid. The name is bound, so text and other names that contain it stay as they are."""
    return rows.withColumn("vid", F.col(column)).filter(F.expr(predicate)).drop("vid")


def edge_matches(edges: DataFrame, edge: QueryEdge, graph: QueryGraph | None = None, semantics: str = "isomorphism", times: bool = False, vertices: DataFrame | None = None) -> DataFrame:
    """Bindings of one query edge: filters only, so that kind and predicates reach the scan.

    times: carry the edge's time as t_lo and t_hi. vertices (vid, vtype, label): where the types and
    labels that the pattern asks of its vertices are looked up.
    """
    rows = edges if edge.etype == ANY else edges.filter(F.col("etype") == edge.etype)
    if edge.predicate:
        rows = rows.filter(F.expr(edge.predicate))
    for v, c in ((edge.src, "src"), (edge.dst, "dst")):
        if graph and (p := graph.predicate(v)):
            rows = at_vertex(rows, p, c)
        known = graph.vertex(v) if graph else None
        if known and (known.vtype or known.label):
            if vertices is None:
                raise ValueError(f"vertex {v} has a type or a label; give a table of vertices")
            fit = vertices.filter(F.col("vtype") == known.vtype) if known.vtype else vertices
            fit = fit.filter(F.col("label").rlike(known.label)) if known.label else fit
            fit = fit.select(F.col("vid").alias("_vid"))
            rows = rows.join(fit, rows[c] == fit["_vid"], "left_semi")
    when = [F.col("ts").alias("t_lo"), F.col("ts").alias("t_hi")] if times else []
    if edge.src == edge.dst:
        return rows.filter("src = dst").select(F.col("src").alias(f"v_{edge.src}"), F.col("eid").alias(f"e_{edge.name}"), *when)
    if semantics == "isomorphism":
        rows = rows.filter("src <> dst")
    return rows.select(F.col("src").alias(f"v_{edge.src}"), F.col("dst").alias(f"v_{edge.dst}"), F.col("eid").alias(f"e_{edge.name}"), *when)


def _apart(left: DataFrame, right: DataFrame, kinds: dict[str, str], semantics: str) -> list[Column]:
    """Vertices that meet first in this join differ; so do edges that can be of one kind."""
    lv, rv = ([c for c in df.columns if c.startswith("v_")] for df in (left, right))
    shared = set(lv) & set(rv)
    out = []
    if semantics == "isomorphism":
        out += [left[a] != right[b] for a in lv for b in rv if a not in shared and b not in shared]
        # A shared vertex was already told apart from the others of its own side.
    le, re_ = ([c for c in df.columns if c.startswith("e_")] for df in (left, right))
    out += [left[a] != right[b] for a, b in itertools.product(le, re_) if kinds[a] == kinds[b] or ANY in (kinds[a], kinds[b])]
    return out


def _mark(vertex: Column) -> Column:
    """Two bytes of a vertex, for lists that do no more than sort out."""
    return F.shiftright(F.hash(vertex), 16).cast("smallint")


def join_bindings(left: DataFrame, right: DataFrame, kinds: dict[str, str], semantics: str = "isomorphism", hint: str | None = None, within: str | None = None) -> DataFrame:
    """left and right joined on the vertices that they share. kinds: e_* column -> kind. within: an interval that all edges lie in, if both sides carry times.

    If right comes from look_ahead, the pairs that the closing edge cannot complete end in this join.
    """
    shared = [c for c in left.columns if c in right.columns and c.startswith("v_")]
    if hint:
        right = right.hint(hint)
    on = [left[c] == right[c] for c in shared] + _apart(left, right, kinds, semantics)
    on += [right[c].isNull() | F.array_contains(right[c], _mark(left[c.removeprefix("to_")])) for c in right.columns if c.startswith("to_")]
    timed = "t_lo" in left.columns and "t_lo" in right.columns
    times = []
    if timed:
        low, high = F.least(left["t_lo"], right["t_lo"]), F.greatest(left["t_hi"], right["t_hi"])
        times = [low.alias("t_lo"), high.alias("t_hi")]
        if within:
            on.append(high <= low + F.expr(f"INTERVAL {within}"))
    joined = left.join(right, reduce(lambda a, b: a & b, on)) if on else left.crossJoin(right)
    names = [[c for c in df.columns if not c.startswith(("t_", "to_"))] for df in (left, right)]
    return joined.select(*[left[c] for c in names[0]], *[right[c] for c in names[1] if c not in shared], *times)


def edge_kinds(tree: JoinTree) -> dict[str, str]:
    return {f"e_{e.name}": e.etype for e in tree.edges}


def leaf_matches(edges: DataFrame, leaf: Leaf, graph: QueryGraph | None = None, semantics: str = "isomorphism", gates: dict[str, DataFrame] | None = None, times: bool = False, vertices: DataFrame | None = None, within: str | None = None) -> DataFrame:
    """Bindings of a piece. gates: vertex -> table with a column vid, and perhaps since_eid; an edge at a gated vertex is looked up there before it is paired."""
    kinds = {f"e_{e.name}": e.etype for e in leaf.edges}
    out = None
    for e in leaf.edges:
        own = edge_matches(edges, e, graph, semantics, times, vertices)
        for v, gate in (gates or {}).items():
            if v in e.ends:
                open_ = own[f"v_{v}"] == gate["vid"]
                if "since_eid" in gate.columns:
                    open_ = open_ & (own[f"e_{e.name}"] > gate["since_eid"])
                own = own.join(gate, open_, "left_semi")
        out = own if out is None else join_bindings(out, own, kinds, semantics, within=within)
    return out


def pair_matches(edges: DataFrame, kind1: str, kind2: str, form: str) -> DataFrame:
    """Two edges at a centre c. form: in-in, out-out, in-out (a to c to b) or out-in (b to c to a)."""
    into = {"a": ("a", "c"), "b": ("b", "c")}
    ends = [into[v] if way == "in" else into[v][::-1] for v, way in zip("ab", form.split("-"), strict=True)]
    return leaf_matches(edges, Leaf((QueryEdge("e0", *ends[0], kind1), QueryEdge("e1", *ends[1], kind2))))


def triad_matches(edges: DataFrame, kinds: tuple[str, str, str], closed: bool) -> DataFrame:
    third = QueryEdge("e2", "c", "a" if closed else "d", kinds[2])
    leaves = [Leaf((QueryEdge("e0", "a", "b", kinds[0]),)), Leaf((QueryEdge("e1", "b", "c", kinds[1]),)), Leaf((third,))]
    return run_tree(edges, JoinTree(tuple(leaves)), QueryGraph(tuple(x.edges[0] for x in leaves)))


def last_eid(columns: list[str]) -> Column:
    names = [c for c in columns if c.startswith("e_")]
    return F.greatest(*names) if len(names) > 1 else F.col(names[0])


def project_cut(bindings: DataFrame, vertices: list[str]) -> DataFrame:
    return bindings.select(*[f"v_{v}" for v in vertices]).distinct()


def gate_rows(prefix: DataFrame, leaf: int) -> DataFrame:
    """vid, leaf, since_eid: from which edge on a vertex of a prefix match is enabled for a leaf."""
    at = [F.col(c) for c in prefix.columns if c.startswith("v_")]
    rows = prefix.select(F.explode(F.array(*at)).alias("vid"), last_eid(prefix.columns).alias("_e"))
    return rows.groupBy("vid").agg(F.min("_e").alias("since_eid")).select("vid", F.lit(leaf).cast("int").alias("leaf"), "since_eid")


def gate_mask(gates: DataFrame) -> DataFrame:
    """vid -> bitmap of the leaves that are enabled there."""
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), F.col("leaf"))
    return gates.groupBy("vid").agg(F.bit_or(bit).alias("mask"))


def gate_edges(edges: DataFrame, gates: DataFrame, leaf: int, at: str = "either") -> DataFrame:
    """Edges with an enabled end: either, src or dst."""
    open_ = gates.filter(F.col("leaf") == leaf).select("vid")
    if at != "either":
        return edges.join(open_, edges[at] == open_["vid"], "left_semi")
    return _either(edges, open_)


def _either(edges: DataFrame, open_: DataFrame) -> DataFrame:
    """Two equi-joins, each of which can be broadcast or shuffled, in place of one join with OR."""
    left = edges.join(open_, edges["src"] == open_["vid"], "left_semi")
    right = edges.join(open_, edges["src"] == open_["vid"], "left_anti").join(open_, edges["dst"] == open_["vid"], "left_semi")
    return left.unionByName(right)


def back_search(history: DataFrame, gates: DataFrame, leaf_edge: QueryEdge, leaf: int) -> DataFrame:
    """Earlier edges of a kind at vertices that were enabled after them: eid, vid, since_eid."""
    rows = history.filter(F.col("etype") == leaf_edge.etype).select("eid", F.explode(F.array("src", "dst")).alias("vid"))
    open_ = gates.filter(F.col("leaf") == leaf).select("vid", "since_eid")
    return rows.join(open_, "vid").filter("eid < since_eid").select("eid", "vid", "since_eid")


def _gates(prefix: DataFrame, at: list[str], i: int, gate: str) -> dict[str, DataFrame]:
    """The vertices at which a piece is searched: those of its own roles, or all of a prefix match."""
    if gate == "vertex":
        return dict.fromkeys(at, gate_rows(prefix, i).select("vid"))
    return {v: project_cut(prefix, [v]).withColumnRenamed(f"v_{v}", "vid") for v in at}


def closing_edge(tree: JoinTree, i: int) -> tuple[QueryEdge, str, str] | None:
    """If leaf i is an edge to a new vertex and leaf i + 1 an edge between that vertex and the prefix before leaf i: the latter, the new vertex, its other end."""
    if not tree.cut(i) or i + 1 == len(tree.leaves) or any(len(x.edges) > 1 for x in tree.leaves[i : i + 2]):
        return None
    (one,), (two,) = tree.leaves[i].edges, tree.leaves[i + 1].edges
    before = tree.prefix_vertices(i - 1)
    for new, other in (two.ends, two.ends[::-1]):
        if new in one.ends and new not in before and other in before:
            return two, new, other
    return None


def look_ahead(own: DataFrame, closing: DataFrame, new: str, other: str) -> DataFrame:
    """own, matches of an edge to a new vertex, with to_v_*: marks of the other ends of the closing edges at that vertex, or null where they are more than MOST_ENDS.

    A prefix that own extends has the other end, so the join that extends it can tell whether a closing
    edge is there. A partial match without one is seen in that join, but neither shuffled nor sorted.
    Matches of own at a vertex without closing edges go. The join with the closing edges stays to be done:
    it finds their edges, and drops what had another vertex's mark.
    """
    at, to = f"v_{new}", f"to_v_{other}"
    nth = F.row_number().over(Window.partitionBy("_at").orderBy("_to"))
    ends = closing.select(F.col(at).alias("_at"), F.col(f"v_{other}").alias("_to")).withColumn("_n", nth).filter(F.col("_n") <= MOST_ENDS + 1)
    ends = ends.groupBy("_at").agg(F.collect_list(_mark(F.col("_to"))).alias("_to"), F.max("_n").alias("_n"))
    ends = ends.select("_at", F.when(F.col("_n") <= MOST_ENDS, F.col("_to")).alias(to))
    return own.join(ends, own[at] == ends["_at"]).drop("_at")


def join_in_slices(left: DataFrame, right: DataFrame, by: str, slices: int, *settings) -> DataFrame:
    """join_bindings by slices of a shared vertex, each stored as it is done, so that the shuffles of one slice are there at a time."""
    if slices < 2:
        return join_bindings(left, right, *settings)
    out = None
    for k in range(slices):
        own = F.pmod(F.xxhash64(by), F.lit(slices)) == k
        rows = passing_table(join_bindings(left.filter(own), right.filter(own), *settings), "slice")
        out = rows if out is None else out.unionByName(rows)
    return out


def run_tree(edges: DataFrame, tree: JoinTree, graph: QueryGraph, gated: bool = False, gate: str = "role", back: bool = True, within: str | None = None, semantics: str = "isomorphism", vertices: DataFrame | None = None) -> DataFrame:
    """All matches: v_* and e_* columns and last_eid, the edge with which the match is complete.

    Ungated, every piece is matched everywhere. Gated, only leaf 0 is; leaf i is matched at vertices
    of the prefix matches. With gate="role" those are its own cut vertices. A piece of one edge, or of
    two that meet in the cut or of which one lies away from it, is joined to the prefix edge by edge,
    the one with more cut vertices first, and that join is the lookup. The two edges of a piece that
    reaches the cut at both ends are looked up first, then paired, and the pair is joined on the whole
    cut, so that no hub at one end is multiplied by the prefix. With gate="vertex" an edge passes at any
    vertex of a match (the bitmap's form). Prefixes that are used twice are checkpointed.
    Where an edge to a new vertex is followed by one that closes a cycle there, the edge is joined with
    look_ahead: all partial matches are seen, those with a closing edge go on to the next join. Large
    graphs do that join in slices, when run_tree is called.
    back=False keeps only leaf matches that are complete after their prefix. within: an interval of
    time, such as "'2' DAY", in which all edges of a match lie; every join tests it.
    """
    kinds, times = edge_kinds(tree), bool(within)
    prefix = leaf_matches(edges, tree.leaves[0], graph, semantics, None, times, vertices, within)
    for i, leaf in enumerate(tree.leaves[1:], 1):
        at = tree.cut(i)
        names = [f"e_{e.name}" for e in leaf.edges]
        before = prefix.columns
        spans = len(leaf.edges) == 2 and leaf.centre not in at and all(set(e.ends) & set(at) for e in leaf.edges)
        ahead = closing_edge(tree, i)
        if ahead:
            closing = edge_matches(edges, ahead[0], graph, semantics, False, vertices)
            slices = min(MOST_SLICES, -(-closing.count() // SLICE_EDGES))
        gates = None
        if gated and at and gate == "role" and not spans:
            pieces = [edge_matches(edges, e, graph, semantics, times, vertices) for e in sorted(leaf.edges, key=lambda e: -len(set(e.ends) & set(at)))]
        else:
            if gated and at:
                prefix = cut(prefix)
                gates = _gates(prefix, at, i, gate)
            pieces = [leaf_matches(edges, leaf, graph, semantics, gates, times, vertices, within)]
        joined = prefix
        for own in pieces:
            if ahead:
                joined = join_in_slices(joined, look_ahead(own, closing, *ahead[1:]), f"v_{at[0]}", slices, kinds, semantics, None, within)
            else:
                joined = join_bindings(joined, own, kinds, semantics, within=within)
        if not back:
            joined = joined.filter(last_eid(names) > last_eid(before))
        prefix = joined
    return prefix.select(*[c for c in prefix.columns if not c.startswith("t_")], last_eid(prefix.columns).alias("last_eid"))


def count_matches(edges: DataFrame, tree: JoinTree, graph: QueryGraph) -> DataFrame:
    """n, the number of matches, without listing them: two pieces, each with one vertex of its own.

    A piece's matches are counted for each binding of the cut and of its own vertex. Of the pairs at a
    binding of the cut, those go in which both own vertices are one. Edges of different pieces then have
    different ends, so they differ too. A piece that is the other one under other names is counted once.
    """
    if len(tree.leaves) != 2:
        raise ValueError("two pieces only")
    at = sorted(tree.cut(1))
    own = [[v for v in x.vertices if v not in at] for x in tree.leaves]
    if not at or any(len(v) != 1 for v in own):
        raise ValueError("each piece needs a cut and one vertex of its own")

    def shape(i: int) -> tuple:
        name = lambda v: "own" if v == own[i][0] else v
        return graph.predicate(own[i][0]), sorted((name(e.src), name(e.dst), e.etype, e.predicate or "") for e in tree.leaves[i].edges)

    sides = [0] if shape(0) == shape(1) else [0, 1]
    rows = None
    for i in sides:
        found = leaf_matches(edges, tree.leaves[i], graph).select(*[f"v_{v}" for v in at], F.col(f"v_{own[i][0]}").alias("own"))
        found = found.withColumns({n: F.lit(int(len(sides) == 1 or k == i)).cast("long") for k, n in enumerate(("one", "two"))})
        rows = found if rows is None else rows.unionByName(found)
    keys = [f"v_{v}" for v in at]
    each = rows.repartition(*keys).groupBy(*keys, "own").agg(F.sum("one").alias("one"), F.sum("two").alias("two"))
    pairs = each.groupBy(*keys).agg((F.sum("one") * F.sum("two") - F.sum(F.col("one") * F.col("two"))).alias("n"))
    return pairs.agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))


def without_look_back(edges: DataFrame, tree: JoinTree, graph: QueryGraph) -> DataFrame:
    """The form that never looks back, for one-edge pieces: an edge that arrives before its vertex is enabled is not searched, and so never stored."""
    kinds, prefix = edge_kinds(tree), leaf_matches(edges, tree.leaves[0], graph)
    for i, leaf in enumerate(tree.leaves[1:], 1):
        if len(leaf.edges) > 1:
            raise ValueError("pieces of one edge only")
        prefix = cut(prefix)
        since = prefix.withColumn("_e", last_eid(prefix.columns))
        gates = {v: since.groupBy(F.col(f"v_{v}").alias("vid")).agg(F.min("_e").alias("since_eid")) for v in tree.cut(i)}
        prefix = join_bindings(prefix, leaf_matches(edges, leaf, graph, gates=gates), kinds)
    return prefix.withColumn("last_eid", last_eid(prefix.columns))


def endpoint_gated(edges: DataFrame, tree: JoinTree, graph: QueryGraph) -> DataFrame:
    """The incomplete form for a one-edge leaf 0 and a two-edge leaf 1: an arriving edge is looked at only if one of its own ends is enabled."""
    all_ = run_tree(edges, tree, graph)
    first, (one, two) = tree.leaves[0].edges[0], tree.leaves[1].edges
    near, far = (one, two) if set(one.ends) & set(first.ends) else (two, one)
    since = cut(gate_rows(leaf_matches(edges, tree.leaves[0], graph), 1).select("vid", "since_eid"))
    out = all_
    for v in far.ends:
        s = since.select(F.col("vid").alias(f"_v{v}"), F.col("since_eid").alias(f"_s{v}"))
        out = out.join(s, out[f"v_{v}"] == s[f"_v{v}"], "left")
    e0, en, ef = (F.col(f"e_{e.name}") for e in (first, near, far))
    enabled = reduce(lambda a, b: a | b, [F.coalesce(F.col(f"_s{v}") < ef, F.lit(False)) for v in far.ends])
    return out.filter((F.greatest(en, ef) < e0) | (en > ef) | enabled).select(*all_.columns)


def canonical_subgraphs(matches: DataFrame) -> DataFrame:
    """Matches that are the same set of edges, once: ``edges``, sorted."""
    names = [c for c in matches.columns if c.startswith("e_")]
    return matches.select(F.array_sort(F.array(*names)).alias("edges")).distinct()


def stored_rows(edges: DataFrame, tree: JoinTree, graph: QueryGraph, gated: bool = False, gate: str = "role") -> DataFrame:
    """leaf, stored: rows that each leaf keeps."""
    return tree_counters(edges, tree, graph, gated, gate).select("leaf", "stored")


def tree_counters(edges: DataFrame, tree: JoinTree, graph: QueryGraph, gated: bool = False, gate: str = "role") -> DataFrame:
    """What a run does, leaf by leaf, whatever the batches: leaf, searches, neighbours, stored, probes, results.

    searches: edges of the piece's kinds around which it is searched (gated, those that pass the gate);
    neighbours: second edges seen at their centres (0 for one edge); stored: matches of the leaf;
    probes: lookups in the sibling, one for each row of either side; results: matches of the joined prefix.
    """
    kinds, out, prefix = edge_kinds(tree), None, None
    for i, leaf in enumerate(tree.leaves):
        gates = None
        if gated and i:
            gates = _gates(prefix, tree.cut(i), i, gate)
        passed = [leaf_matches(edges, Leaf((e,)), graph, gates=gates) for e in leaf.edges]
        searches = reduce(lambda a, b: a.unionByName(b), [x.select(F.col(f"e_{e.name}").alias("e")) for x, e in zip(passed, leaf.edges, strict=True)]).agg(F.count("*").alias("searches"))
        row = searches
        if len(leaf.edges) == 2:
            one, two = (x.groupBy(F.col(f"v_{leaf.centre}").alias("c")).agg(F.count("*").alias(n)) for x, n in zip(passed, ("n", "m"), strict=True))
            row = row.join(F.broadcast(one.join(two, "c").agg(F.coalesce(F.sum(F.col("n") * F.col("m")), F.lit(0)).cast("long").alias("neighbours"))))
        else:
            row = row.withColumn("neighbours", F.lit(0).cast("long"))
        own = cut(leaf_matches(edges, leaf, graph, gates=gates))
        row = row.join(F.broadcast(own.agg(F.count("*").alias("stored"))))
        if prefix is None:
            prefix = own
            row = row.withColumn("probes", F.lit(0).cast("long")).withColumn("results", F.col("stored"))
        else:
            rows = prefix.count()
            prefix = cut(join_bindings(prefix, own, kinds))
            row = row.withColumn("probes", F.col("stored") + F.lit(rows).cast("long")).join(F.broadcast(prefix.agg(F.count("*").alias("results"))))
        row = row.select(F.lit(i).cast("int").alias("leaf"), "searches", "neighbours", "stored", "probes", "results")
        out = row if out is None else out.unionByName(row)
    return out

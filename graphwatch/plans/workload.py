"""The experiments' patterns, fixed ones and random ones. Randomness is seeded Python, so runs agree."""

from __future__ import annotations

import random
from itertools import combinations_with_replacement

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphwatch.model import QueryEdge, QueryGraph, pattern
from graphwatch.plans.cutting import Statistics, cut_pattern, expected_selectivity, pair_signature
from graphwatch.sources.graphs import BITS

FACETS = ("customer", "nation", "part", "supplier")

#: The patterns of the catalogue, by graph and name.
HOST = {
    "host_path2": pattern("a -k4> b", "b -k0> c"),
    "host_path3": pattern("a -k4> b", "b -k0> c", "c -k1> d"),
    "host_path4": pattern("a -k5> b", "b -k2> c", "c -k3> d", "d -k1> e"),
    "host_path5": pattern("a -k5> b", "b -k3> c", "c -k2> d", "d -k3> e", "e -k2> f"),
    "host_path5r": pattern("a -k6> b", "b -k3> c", "c -k2> d", "d -k3> e", "e -k1> f"),
    "host_tree5": pattern("a -k4> b", "a -k3> c", "b -k2> d", "b -k3> e"),
    "host_tree7": pattern("a -k5> b", "a -k4> c", "b -k3> d", "b -k2> e", "c -k3> f", "c -k4> g"),
    "host_cycle3": pattern("a -k3> b", "b -k2> c", "c -k1> a"),
    "labeled_path": pattern("a -k4> b", "b -k0> c", a="vid < 10"),
}
COMMUNITY = {
    "community_path4": pattern("a -c0> b", "b -c1> c", "c -c2> d", "d -c3> e"),
    "community_path4m": pattern("a -c1> b", "b -c3> c", "c -c3> d", "d -c1> e"),
    "community_path4n": pattern("a -c1> b", "b -c4> c", "c -c4> d", "d -c1> e"),
    "community_path4s": pattern("a -c0> b", "b -c0> c", "c -c1> d", "d -c1> e"),
}
SOCIAL = {
    "social_path3": pattern("c -places> o", "o -has_AF> p", "p -brand> b"),
    "social_path4": pattern("c -places> o", "o -has_AF> p", "p -brand> b", "c -in_nation> n"),
    "social_path5": pattern("c -places> o", "o -has_AF> p", "p -brand> b", "c -in_nation> n", "n -in_region> r"),
    "social_tree4": pattern("c -in_nation> n", "c -segment> s", "c -places> o", "o -status> t"),
    "social_tree5": pattern("c -places> o", "o -prio> p", "o -status> s", "o -has_AF> x", "o -has_NO> y"),
    "social_tree6": pattern("c -places> o", "o -prio> p", "o -has_AF> x", "x -brand> b", "o -has_NO> y", "y -brand> d"),
    "social_act4": pattern("c -places> o", "s -ships_RF> o", "c -purchase> j", "c -in_nation> n"),
}


def facet_diamond(a: str, b: str) -> QueryGraph:
    """Two articles that share a facet of each of two kinds."""
    return pattern(f"a -{a}> x", f"a -{b}> y", f"b -{a}> x", f"b -{b}> y")


def facet_diamonds() -> dict[str, QueryGraph]:
    return {f"diamond_{a}_{b}": facet_diamond(a, b) for a, b in combinations_with_replacement(FACETS, 2)}


def random_path(k: int, kinds: list[str], seed: int) -> QueryGraph:
    r = random.Random(seed)
    return QueryGraph(tuple(QueryEdge(f"e{i}", f"v{i}", f"v{i + 1}", r.choice(kinds)) for i in range(k)))


def random_binary_tree(n: int, kinds: list[str], seed: int) -> QueryGraph:
    r = random.Random(seed)
    return QueryGraph(tuple(QueryEdge(f"e{i - 1}", f"v{(i - 1) // 2}", f"v{i}", r.choice(kinds)) for i in range(1, n)))


def valid_triples(edges: DataFrame, cube: bool = False) -> DataFrame:
    """(type code of the source, kind, type code of the target) with their number; cube: and the sums over any of the three."""
    code = lambda c: F.call_function("shiftright", F.col(c), F.lit(BITS)).cast("int")
    keys = [code("src").alias("src_type"), F.col("etype"), code("dst").alias("dst_type")]
    return (edges.cube(*keys) if cube else edges.groupBy(*keys)).agg(F.count("*").alias("n"))


def random_typed_tree(n_edges: int, triples: list[tuple], seed: int, path: bool = False) -> QueryGraph:
    """Grown edge by edge: each new edge is a valid triple at a vertex that is there already (at the last one, for a path)."""
    r, triples = random.Random(seed), sorted(triples)
    s, kind, t = r.choice(triples)
    types, edges = {"v0": s, "v1": t}, [QueryEdge("e0", "v0", "v1", kind)]
    while len(edges) < n_edges:
        at = f"v{len(types) - 1}" if path else r.choice(sorted(types))
        options = [x for x in triples if types[at] in (x[0], x[2])]
        s, kind, t = r.choice(options)
        new, out = f"v{len(types)}", types[at] == s
        types[new] = t if out else s
        edges.append(QueryEdge(f"e{len(edges)}", *((at, new) if out else (new, at)), kind))
    return QueryGraph(tuple(edges))


def random_typed_path(n_edges: int, triples: list[tuple], seed: int) -> QueryGraph:
    return random_typed_tree(n_edges, triples, seed, path=True)


#: Triples of the social graph between vertices that have few edges of that kind each.
SOCIAL_TRIPLES = [("customer", "places", "order"), ("order", "has_AF", "part"), ("order", "has_NO", "part"), ("supplier", "from_nation", "nation"), ("customer", "segment", "segment"), ("nation", "in_region", "region")]


def random_social(n_edges: int, n: int, path: bool) -> dict[str, QueryGraph]:
    """n random typed paths or trees of the social graph that go through its activity; leaves at hubs are reached by one edge only."""
    out, seed = {}, 0
    while len(out) < n:
        g = random_typed_tree(n_edges, SOCIAL_TRIPLES, seed, path)
        hubs = [v for v in g.vertex_names if sum(v in e.ends for e in g.edges) > 1 and any(e.etype in ("segment", "from_nation", "in_region") and e.dst == v for e in g.edges)]
        kinds = [e.etype for e in g.edges]
        if not hubs and "places" in kinds and max(map(kinds.count, kinds)) < 3:
            out[f"{'path' if path else 'tree'}{seed}"] = g
        seed += 1
    return out


def filter_seen(group: list[QueryGraph], known: Statistics) -> list[QueryGraph]:
    """Without those that have two edges at a vertex which the statistics never saw together."""
    def seen(g: QueryGraph) -> bool:
        return all(pair_signature(a, b, v) in known.pairs for i, a in enumerate(g.edges) for b in g.edges[i + 1 :] for v in set(a.ends) & set(b.ends))

    return [g for g in group if seen(g)]


def uniform_by_selectivity(group: list[QueryGraph], known: Statistics, n: int, bins: int = 10) -> list[QueryGraph]:
    """n of the group, spread over equal bins of the logarithm of the expected selectivity, in turn."""
    scored = [(s, i) for i, g in enumerate(group) if (s := expected_selectivity(cut_pattern(g, known), known)) is not None]
    if not scored:
        return []
    low, high = min(scored)[0], max(scored)[0]
    rows: list[list[int]] = [[] for _ in range(bins)]
    for s, i in scored:
        rows[min(bins - 1, int((s - low) / ((high - low) or 1) * bins))].append(i)
    out: list[int] = []
    while len(out) < min(n, len(scored)):
        for row in rows:
            if row and len(out) < n:
                out.append(row.pop(0))
    return [group[i] for i in sorted(out)]

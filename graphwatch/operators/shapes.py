"""Join trees of other shapes than left-deep, for comparison."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphwatch.model import ANY, JoinTree, QueryGraph
from graphwatch.operators.matching import edge_kinds, join_bindings, last_eid, leaf_matches


def run_bushy(edges: DataFrame, tree: JoinTree, graph: QueryGraph) -> DataFrame:
    """The leaves joined two by two, level by level, each with the next one that it shares a vertex with."""
    kinds, nodes = edge_kinds(tree), [leaf_matches(edges, x, graph) for x in tree.leaves]
    while len(nodes) > 1:
        level, rest = [], list(nodes)
        while rest:
            one = rest.pop(0)
            mine = {c for c in one.columns if c.startswith("v_")}
            other = next((x for x in rest if mine & set(x.columns)), None)
            if other is None:
                level.append(one)
                continue
            rest = [x for x in rest if x is not other]
            level.append(join_bindings(one, other, kinds))
        if len(level) == len(nodes):
            raise ValueError("the pieces do not hang together")
        nodes = level
    return nodes[0].withColumn("last_eid", last_eid(nodes[0].columns))


def run_n_ary(edges: DataFrame, tree: JoinTree, graph: QueryGraph) -> DataFrame:
    """One node over all leaves: combined on shared vertices alone, and only complete combinations are tested for distinct vertices and edges."""
    kinds = edge_kinds(tree)
    out = leaf_matches(edges, tree.leaves[0], graph)
    for leaf in tree.leaves[1:]:
        own = leaf_matches(edges, leaf, graph)
        shared = [c for c in out.columns if c in own.columns]
        on = reduce(lambda a, b: a & b, [out[c] == own[c] for c in shared]) if shared else None
        joined = out.crossJoin(own) if on is None else out.join(own, on)
        out = joined.select(*[out[c] for c in out.columns], *[own[c] for c in own.columns if c not in shared])
    v, e = ([c for c in out.columns if c.startswith(p)] for p in ("v_", "e_"))
    apart = [F.col(a) != F.col(b) for i, a in enumerate(v) for b in v[i + 1 :]]
    apart += [F.col(a) != F.col(b) for i, a in enumerate(e) for b in e[i + 1 :] if kinds[a] == kinds[b] or ANY in (kinds[a], kinds[b])]
    if apart:
        out = out.filter(reduce(lambda a, b: a & b, apart))
    return out.withColumn("last_eid", last_eid(out.columns))

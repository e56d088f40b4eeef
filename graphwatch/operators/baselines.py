"""What incremental gated matching is compared with."""

from __future__ import annotations

import uuid
from collections import defaultdict

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphwatch.functions.storage import scratch_path, table
from graphwatch.model import ANY, JoinTree, Leaf, QueryEdge, QueryGraph
from graphwatch.operators.matching import run_tree


def backtrack(rows: list[tuple], graph: QueryGraph) -> list[dict]:
    """All matches by backtracking over (eid, src, dst, etype) rows, in memory."""
    by_kind, out_of, into = defaultdict(list), defaultdict(list), defaultdict(list)
    for r in rows:
        by_kind[r[3]].append(r)
        out_of[r[3], r[1]].append(r)
        into[r[3], r[2]].append(r)
    left, order, bound = list(graph.edges), [], set()
    while left:
        e = next((e for e in left if bound & set(e.ends)), left[0])
        left.remove(e)
        order.append(e)
        bound |= set(e.ends)
    found: list[dict] = []

    def extend(i: int, v: dict, e: dict):
        if i == len(order):
            found.append({f"v_{k}": x for k, x in v.items()} | {f"e_{k}": x for k, x in e.items()} | {"last_eid": max(e.values())})
            return
        q = order[i]
        options = out_of[q.etype, v[q.src]] if q.src in v else into[q.etype, v[q.dst]] if q.dst in v else by_kind[q.etype]
        for eid, src, dst, _ in options:
            if eid in e.values() or (q.src == q.dst) != (src == dst):
                continue
            more = dict(v)
            for name, x in ((q.src, src), (q.dst, dst)):
                if more.get(name, x) != x or name not in more and x in more.values():
                    break
                more[name] = x
            else:
                extend(i + 1, more, e | {q.name: eid})

    extend(0, {}, {})
    return found


#: A baseline that holds the whole graph in one worker takes no more edges than this.
MOST_EDGES = 5_000_000


def _held(edges: DataFrame, graph: QueryGraph) -> DataFrame:
    """The edges that a search can use; refuses more than a worker holds, as these baselines cannot do without."""
    kinds = {e.etype for e in graph.edges}
    rows = edges.select("eid", "src", "dst", "etype")
    rows = rows if ANY in kinds else rows.filter(F.col("etype").isin(*kinds))
    if (n := rows.count()) > MOST_EDGES:
        raise ValueError(f"{n} edges: a search that holds the whole graph takes up to {MOST_EDGES}")
    return rows


def _names(graph: QueryGraph) -> list[str]:
    return [f"v_{v}" for v in graph.vertex_names] + [f"e_{e.name}" for e in graph.edges]


def backtrack_matches(edges: DataFrame, graph: QueryGraph) -> DataFrame:
    """Whole-pattern backtracking over all edges, in one group: a baseline that does not scale, and refuses what is too large."""
    names = [*_names(graph), "last_eid"]

    def search(pdf: pd.DataFrame) -> pd.DataFrame:
        rows = list(pdf[["eid", "src", "dst", "etype"]].itertuples(index=False, name=None))
        return pd.DataFrame(backtrack(rows, graph), columns=names).astype("int64")

    return _held(edges, graph).withColumn("g", F.lit(0)).groupBy("g").applyInPandas(search, ", ".join(f"{n} long" for n in names))


class _Held:
    """Edges by kind and end, those of an end in order of arrival."""

    def __init__(self, kinds: dict[str, tuple[np.ndarray, np.ndarray, np.ndarray]]):
        self.kinds, self.at = kinds, {}
        for kind, (eid, src, dst) in kinds.items():
            for side, end in ((0, src), (1, dst)):
                order = np.lexsort((eid, end))
                self.at[kind, side] = end[order], eid[order], src[order], dst[order]

    def edges(self, kind: str, side: int, vertex: int, before: int):
        """(eid, src, dst) of the edges of a kind with that source (side 0) or target (1) which came before an arrival."""
        if (kind, side) not in self.at:
            return ()
        end, eid, src, dst = self.at[kind, side]
        a, b = end.searchsorted(vertex), end.searchsorted(vertex, "right")
        b = a + eid[a:b].searchsorted(before)
        return zip(eid[a:b].tolist(), src[a:b].tolist(), dst[a:b].tolist(), strict=True)


def _order_from(graph: QueryGraph, first: QueryEdge) -> list[QueryEdge]:
    """All query edges, each next one touching those before."""
    order, left, bound = [first], [e for e in graph.edges if e is not first], set(first.ends)
    while left:
        e = next(e for e in left if bound & set(e.ends))
        left.remove(e)
        order.append(e)
        bound |= set(e.ends)
    return order


def _through(held: _Held, order: list[QueryEdge], edge: tuple[int, int, int], before: int):
    """Matches in which the first query edge is the given edge, and all others came before an arrival: bindings of vertices and of edges."""

    def extend(i: int, options, v: dict, e: dict):
        q = order[i]
        for eid, src, dst in options:
            if eid in e.values() or (q.src == q.dst) != (src == dst):
                continue
            more = dict(v)
            for name, x in ((q.src, src), (q.dst, dst)):
                if more.get(name, x) != x or name not in more and x in more.values():
                    break
                more[name] = x
            else:
                if i + 1 == len(order):
                    yield more, e | {q.name: eid}
                    continue
                n = order[i + 1]
                side = 0 if n.src in more else 1
                yield from extend(i + 1, held.edges(n.etype, side, more[n.dst if side else n.src], before), more, e | {q.name: eid})

    return extend(0, [edge], {}, {})


def rematch_per_edge(edges: DataFrame, graph: QueryGraph) -> DataFrame:
    """A search after each edge, reporting what the search before did not find: as many searches as edges of the pattern's kinds.

    Edges are dealt to tasks by ranges of arrival; each task holds the whole graph. It searches the graph as it was before its range
    once, and after each edge of the range around that edge: a match stays one, so all others were found before. Adds
    ``reported``, the edge after which a match was found, and ``found``, the matches that a full search would find then.
    """
    spark = edges.sparkSession
    rows, columns = _held(edges, graph), [*_names(graph), "last_eid", "reported", "found"]
    kinds, vertices, names = {e.etype for e in graph.edges}, graph.vertex_names, [e.name for e in graph.edges]
    got = rows.toArrow()
    etype, numbers = got.column("etype").to_numpy(), [got.column(c).to_numpy() for c in ("eid", "src", "dst")]
    sent = spark.sparkContext.broadcast({k: tuple(x[etype == k] for x in numbers) for k in kinds})
    del got, etype, numbers

    def search(batches):
        held, found = None, 0
        orders = {q.name: _order_from(graph, q) for q in graph.edges}
        for pdf in batches:
            out = []
            for eid, src, dst, kind in zip(*(pdf[c].tolist() for c in ("eid", "src", "dst", "etype")), strict=True):
                if held is None:
                    held, first = _Held(sent.value), graph.edges[0]
                    early = (e for e in zip(*(x.tolist() for x in held.kinds[first.etype]), strict=True) if e[0] < eid)
                    found = sum(1 for e in early for _ in _through(held, orders[first.name], e, eid))
                new = [m for q in graph.edges if q.etype == kind for m in _through(held, orders[q.name], (eid, src, dst), eid)]
                found += len(new)
                out += [(*(v[x] for x in vertices), *(e[x] for x in names), eid, eid, found) for v, e in new]
            yield pd.DataFrame(out, columns=columns).astype("int64")

    dealt = rows.repartitionByRange(4 * spark.sparkContext.defaultParallelism, "eid").sortWithinPartitions("eid")
    return dealt.mapInPandas(search, ", ".join(f"{x} long" for x in columns))


def _one_edge_tree(graph: QueryGraph) -> JoinTree:
    """Edges in the pattern's order, each next one touching those before."""
    left, leaves, seen = list(graph.edges), [], set()
    while left:
        e = next((e for e in left if not seen or seen & set(e.ends)), left[0])
        left.remove(e)
        leaves.append(Leaf((e,)))
        seen |= set(e.ends)
    return JoinTree(tuple(leaves))


def flat_join(edges: DataFrame, graph: QueryGraph) -> DataFrame:
    """One chain of joins in the pattern's own order; what Spark makes of it is its affair."""
    return run_tree(edges, _one_edge_tree(graph), graph)


def rematch_every(edges: DataFrame, graph: QueryGraph, batches: int, n_edges: int, counted: bool = False) -> DataFrame:
    """Full search after each of some equal batches; new matches are those that were not there before: they end with an edge of the batch.

    counted: instead, batch, found and redundant (matches that an earlier search had found).
    """
    size, before, out = -(-n_edges // batches), None, None
    for b in range(batches):
        now = table(flat_join(edges.filter(F.col("eid") < (b + 1) * size), graph), "rematch")
        if counted:
            again = F.lit(0).cast("long") if before is None else F.lit(before.count())
            new = now.agg(F.count("*").alias("found")).select(F.lit(b).cast("long").alias("batch"), "found", again.alias("redundant"))
        else:
            new = now.filter(F.col("last_eid") >= b * size)
        out = new if out is None else out.unionByName(new)
        before = now
    return out


def pattern_radius(graph: QueryGraph) -> int:
    """Longest shortest path between two vertices, whatever the directions."""
    near = defaultdict(set)
    for e in graph.edges:
        near[e.src].add(e.dst)
        near[e.dst].add(e.src)
    most = 0
    for start in graph.vertex_names:
        seen, ring, d = {start}, {start}, 0
        while ring := {u for v in ring for u in near[v]} - seen:
            seen |= ring
            d += 1
        most = max(most, d)
    return most


def rematch_neighbourhood(history: DataFrame, delta: DataFrame, graph: QueryGraph) -> DataFrame:
    """New matches of a batch, searched only within the pattern's radius around its edges."""
    wanted = [e.etype for e in graph.edges]
    every = history.unionByName(delta).filter(F.col("etype").isin(wanted))
    touched = table(delta.select(F.explode(F.array("src", "dst")).alias("vid")).distinct(), "ball")
    for _ in range(pattern_radius(graph)):
        ends = every.select("src", "dst")
        out = ends.join(touched, ends["src"] == touched["vid"], "left_semi").select(F.col("dst").alias("vid"))
        back = ends.join(touched, ends["dst"] == touched["vid"], "left_semi").select(F.col("src").alias("vid"))
        touched = table(touched.unionByName(out).unionByName(back).distinct(), "ball")
    ball = every.join(touched, every["src"] == touched["vid"], "left_semi").join(touched, F.col("dst") == touched["vid"], "left_semi")
    found = flat_join(ball, graph)
    new = delta.select("eid")
    return found.join(new, found["last_eid"] == new["eid"], "left_semi")


def adjacency_index(edges: DataFrame, name: str, path: str, buckets: int = 8) -> str:
    """Edges bucketed by source and sorted by kind, as an external table at path: joins by source then need no exchange. Rebuilt whole."""
    edges.write.mode("overwrite").option("path", path).bucketBy(buckets, "src").sortBy("src", "etype").saveAsTable(name)
    return name


def indexed_rematch(edges: DataFrame, graph: QueryGraph, rebuilds: int, n_edges: int) -> DataFrame:
    """The index is rebuilt after each of some equal batches, and the last one answers the pattern."""
    size, spark = -(-n_edges // rebuilds), edges.sparkSession
    for b in range(rebuilds):
        name = adjacency_index(edges.filter(F.col("eid") < (b + 1) * size), f"adjacency_{uuid.uuid4().hex}", scratch_path(spark, "adjacency"))
    return flat_join(spark.table(name), graph)

"""Incremental matching: batches of edges against stored partial matches."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphwatch.functions.state import StateStore
from graphwatch.functions.storage import scratch_path
from graphwatch.model import ANY, JoinTree, Leaf, QueryGraph
from graphwatch.operators.matching import edge_kinds, edge_matches, join_bindings, last_eid, leaf_matches, project_cut


def _union(parts: list[DataFrame | None]) -> DataFrame | None:
    have = [p for p in parts if p is not None]
    return reduce(lambda a, b: a.unionByName(b), have) if have else None


class DeltaMatcher:
    """Keeps the matches of each tree node; a batch adds to them and gives the new full matches.

    New matches of a join are new left with old right, old left with new right, and new with new, so
    each comes out once. Gated, a leaf's matches are kept only at vertices of its prefix: those of a new
    batch at all enabled vertices, and earlier ones at vertices that this batch enables (back-search).
    What is enabled is a table of its own to which a batch adds the cuts of its new prefix matches only;
    edges are looked up there before they are paired.

    State is in the folder ``path`` (a new one in the shared folder if none is given). A matcher that is
    made on a folder with commits goes on where the last one ended; a batch number that is committed
    already gives the same result again and changes nothing. Every ``fanout`` batches a table's parts
    are merged into one.

    within: an interval in which all edges of a match lie. Batches must then come in the order of time;
    merging drops rows that are older than that, as they can take part in no new match.
    """

    def __init__(self, tree: JoinTree, graph: QueryGraph, gated: bool = False, semantics: str = "isomorphism", path: str | None = None, within: str | None = None, fanout: int = 8):
        self.tree, self.graph, self.gated, self.semantics = tree, graph, gated, semantics
        self.path, self.within, self.fanout = path, within, fanout
        self.kinds = edge_kinds(tree)
        self.store: StateStore | None = None

    def _open(self, spark) -> StateStore:
        if self.store is None:
            self.path = self.path or scratch_path(spark, "watch")
            self.store = StateStore(spark, self.path, self.fanout)
        return self.store

    def _edges(self, rows: DataFrame, e, gates: dict[str, DataFrame] | None) -> DataFrame:
        out = edge_matches(rows, e, self.graph, self.semantics, bool(self.within))
        for v, open_ in (gates or {}).items():
            if v in e.ends:
                out = out.join(open_, out[f"v_{v}"] == open_["vid"], "left_semi")
        return out

    def _new_leaf(self, leaf: Leaf, batch: DataFrame, history: DataFrame | None, gates: dict[str, DataFrame] | None) -> DataFrame:
        """Matches of a piece with an edge of the batch. Edges are looked up in the gates first, then paired."""
        if len(leaf.edges) == 1:
            return self._edges(batch, leaf.edges[0], gates)
        one, two = leaf.edges
        new = [self._edges(batch, e, gates) for e in (one, two)]
        old = [None if history is None else self._edges(history, e, gates) for e in (one, two)]
        parts = [(new[0], new[1]), (new[0], old[1]), (old[0], new[1])]
        return _union([join_bindings(a, b, self.kinds, self.semantics, within=self.within) for a, b in parts if a is not None and b is not None])

    def advance(self, batch: DataFrame, number: int | None = None) -> DataFrame:
        """The full matches that the batch completes, with last_eid. number: of the batch, rising; one that is committed is not done again."""
        store = self._open(batch.sparkSession)
        number = store.last + 1 if number is None else number
        if number <= store.last:
            if number < store.last:
                raise ValueError(f"batch {number} came again after batch {store.last}")
            return self._shown(store.read_result())
        wanted = {e.etype for e in self.tree.edges}
        if ANY not in wanted:
            batch = batch.filter(F.col("etype").isin(*wanted))
        history, leaves = store.read("edges"), [store.read(f"leaf{i}") for i in range(len(self.tree.leaves))]
        nodes, keys = [store.read(f"node{i}") for i in range(len(self.tree.leaves))], [store.read(f"keys{i}") for i in range(len(self.tree.leaves))]
        batch = store.write("edges", batch.select("eid", "src", "dst", "etype", "ts"))
        added, old = store.write("node0", self._new_leaf(self.tree.leaves[0], batch, history, None)), nodes[0]
        for i, leaf in enumerate(self.tree.leaves[1:], 1):
            if self.gated and self.tree.cut(i):
                at = self.tree.cut(i)
                names = [f"v_{v}" for v in at]
                fresh = project_cut(added, at)
                if keys[i] is not None:
                    fresh = fresh.join(keys[i], names, "left_anti")
                fresh = store.write(f"keys{i}", fresh)
                enabled = _union([keys[i], fresh])
                gates = {v: enabled.select(F.col(f"v_{v}").alias("vid")).distinct() for v in at}
                found = self._new_leaf(leaf, batch, history, gates)
                if len(at) > 1:
                    found = found.join(enabled, names, "left_semi")
                if history is not None:
                    first = {v: fresh.select(F.col(f"v_{v}").alias("vid")).distinct() for v in at}
                    earlier = leaf_matches(history, leaf, self.graph, self.semantics, first, bool(self.within), within=self.within)
                    found = found.unionByName(earlier.join(fresh, names, "left_semi"))
            else:
                found = self._new_leaf(leaf, batch, history, None)
            found = store.write(f"leaf{i}", found)
            parts = [(added, found), (added, leaves[i]), (old, found)]
            new = _union([join_bindings(a, b, self.kinds, self.semantics, within=self.within) for a, b in parts if a is not None and b is not None])
            added, old = store.write(f"node{i}", new), nodes[i]
        store.keep_result(f"node{len(self.tree.leaves) - 1}")
        self._merge(batch)
        store.commit(number)
        return self._shown(store.read_result())

    def _merge(self, batch: DataFrame) -> None:
        """Merge the parts of tables that have many, all at once, so that what is dropped is dropped everywhere."""
        store = self.store
        if not store.full("edges"):
            return
        since = batch.agg(F.max("ts").alias("now")).select((F.col("now") - F.expr(f"INTERVAL {self.within}")).alias("since")) if self.within else None

        def young(rows: DataFrame, time: str) -> DataFrame:
            return rows if since is None else rows.join(F.broadcast(since), F.col(time) >= F.col("since"), "left_semi")

        store.replace("edges", young(store.read("edges"), "ts"))
        for i, _ in enumerate(self.tree.leaves):
            rows, gate = store.read(f"leaf{i}"), store.read(f"keys{i}")
            if i:
                if gate is not None and since is not None:
                    # A key stays while a match of its prefix does; leaf matches at other keys go too, and are looked for again if they are enabled again.
                    gate = project_cut(store.read(f"node{i - 1}"), self.tree.cut(i))
                if gate is not None:
                    store.replace(f"keys{i}", gate)
                rows = young(rows, "t_lo")
                if gate is not None and since is not None:
                    rows = rows.join(store.read(f"keys{i}"), [f"v_{v}" for v in self.tree.cut(i)], "left_semi")
                store.replace(f"leaf{i}", rows)
            if store.read(f"node{i}") is not None and i < len(self.tree.leaves) - 1:
                store.replace(f"node{i}", young(store.read(f"node{i}"), "t_lo"))
        if len(self.tree.leaves) > 0:
            last = f"node{len(self.tree.leaves) - 1}"
            store.replace(last, store.read(last))

    @staticmethod
    def _shown(rows: DataFrame) -> DataFrame:
        return rows.select(*[c for c in rows.columns if not c.startswith("t_")], last_eid(rows.columns).alias("last_eid"))

    def snapshot(self) -> DataFrame:
        """All full matches so far."""
        return self._shown(self.store.read(f"node{len(self.tree.leaves) - 1}"))

    def stored(self) -> dict[str, int]:
        """Rows of each table of the state."""
        return {name: self.store.read(name).count() for name in sorted(self.store.parts)}


class AdaptiveMatcher:
    """A matcher that cuts its pattern anew when the order of its pieces has changed.

    After every ``every`` batches statistics are taken from the edges so far. If the plan's pieces no
    longer ascend, the pattern is cut again; the new plan's partial matches come from one batch run over
    the stored edges, and the old state is left. What was reported is not reported again.
    """

    def __init__(self, tree: JoinTree, graph: QueryGraph, recut: Callable[[DataFrame], JoinTree | None], every: int = 2, gated: bool = True):
        self.graph, self.recut, self.every, self.gated = graph, recut, every, gated
        self.matcher, self.seen, self.migrations = DeltaMatcher(tree, graph, gated), 0, 0

    def advance(self, batch: DataFrame) -> DataFrame:
        out = self.matcher.advance(batch)
        self.seen += 1
        if self.seen % self.every == 0:
            edges = self.matcher.store.read("edges")
            tree = self.recut(edges)
            if tree is not None and tree.leaves != self.matcher.tree.leaves:
                moved = DeltaMatcher(tree, self.graph, self.gated)
                moved.advance(edges)
                self.matcher, self.migrations = moved, self.migrations + 1
        return out

    def snapshot(self) -> DataFrame:
        return self.matcher.snapshot()


def advance_all(edges: DataFrame, tree: JoinTree, graph: QueryGraph, batches: int, n_edges: int, gated: bool = False) -> DataFrame:
    """The stream in equal batches by eid; the union of what they report."""
    matcher, size = DeltaMatcher(tree, graph, gated), -(-n_edges // batches)
    for b in range(batches):
        matcher.advance(edges.filter((F.col("eid") >= b * size) & (F.col("eid") < (b + 1) * size)))
    return matcher.snapshot()

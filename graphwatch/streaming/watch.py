"""Continuous matching: chained stream-stream joins, batches with stored state, or state for each vertex."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphwatch.model import JoinTree, QueryGraph
from graphwatch.operators.delta import DeltaMatcher
from graphwatch.operators.matching import edge_kinds, edge_matches, join_bindings, last_eid


def watch_joins(source: DataFrame, tree: JoinTree, graph: QueryGraph, watermark: str = "3650 days", within: str | None = None) -> DataFrame:
    """A streaming DataFrame of matches for a tree of one-edge leaves: one inner join for each leaf after the first.

    Each branch has its watermark; only one event-time column outlives a join, so times of the
    prefix become numbers. Rows later than the watermark are dropped. within: an interval in which all
    edges lie; with two leaves Spark drops state that can meet no more edges by it.
    """
    if any(len(x.edges) > 1 for x in tree.leaves):
        raise ValueError("chained stream joins take one-edge leaves; use watch_batches")
    kinds, prefix = edge_kinds(tree), None
    for i, leaf in enumerate(tree.leaves):
        rows = edge_matches(source.withWatermark("ts", watermark), leaf.edges[0], graph, times=True).withColumnRenamed("t_lo", f"t{i}").drop("t_hi")
        if prefix is None:
            prefix = rows
        elif within and i == 1:
            # The time bound is part of the join, in event time on both sides.
            bound = f"t1 BETWEEN t0 - INTERVAL {within} AND t0 + INTERVAL {within}"
            joined = join_bindings(prefix, rows, kinds).filter(F.expr(bound))
            prefix = joined.withColumn("t0", F.unix_micros("t0"))
        else:
            prefix = join_bindings(prefix.withColumn(f"t{i - 1}", F.unix_micros(f"t{i - 1}")), rows, kinds)
    times = [f"t{i}" for i in range(len(tree.leaves))]
    if within and len(times) > 1:
        number = [F.col(t) if i < len(times) - 1 else F.unix_micros(t) for i, t in enumerate(times)]
        span = F.unix_micros(F.timestamp_micros(F.least(*number)) + F.expr(f"INTERVAL {within}"))
        prefix = prefix.filter(F.greatest(*number) <= span)
    return prefix.drop(*times).withColumn("last_eid", last_eid(prefix.columns))


def watch_batches(source: DataFrame, tree: JoinTree, graph: QueryGraph, report: Callable[[DataFrame, int], None], checkpoint: str, gated: bool = True, within: str | None = None):
    """Start a query whose batches run through a DeltaMatcher; report gets the new matches of each batch.

    The matcher's state lies below the checkpoint and is committed by batch number: after a restart the
    query goes on with it, and a batch that Spark sends again reports the same matches again.
    """
    matcher = DeltaMatcher(tree, graph, gated, path=f"{checkpoint.rstrip('/')}/matcher", within=within)

    def step(batch: DataFrame, number: int) -> None:
        report(matcher.advance(batch.select("eid", "src", "dst", "etype", "ts"), number), number)

    return source.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).start()


def watch_pairs(source: DataFrame, rare: str, common: str, keep: str = "3650 days", watermark: str = "3650 days") -> DataFrame:
    """Gated matching of a -rare> b -common> c with state of our own for each b: eid_rare, eid_common, a, b, c.

    A common edge is only remembered (the history that a back-search needs) until a rare edge reaches
    its vertex; that enables the vertex, and matches come out as edges arrive. A vertex whose last edge
    is older than ``keep`` loses its state once the watermark has passed.
    """
    rows = source.filter(F.col("etype").isin(rare, common) & (F.col("src") != F.col("dst"))).withWatermark("ts", watermark)
    rows = rows.withColumn("b", F.when(F.col("etype") == rare, F.col("dst")).otherwise(F.col("src")))
    millis = int(pd.Timedelta(keep).total_seconds() * 1000)

    def step(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        r_eid, r_end, c_eid, c_end = (list(x) for x in state.get) if state.exists else ([], [], [], [])
        out, latest = [], 0
        for pdf in batches:
            for row in pdf.sort_values("eid").itertuples():
                latest = max(latest, int(row.ts.timestamp() * 1000))
                if row.etype == rare:
                    out += [(row.eid, e, row.src, key[0], x) for e, x in zip(c_eid, c_end, strict=True) if x != row.src]
                    r_eid.append(row.eid), r_end.append(row.src)
                else:
                    out += [(e, row.eid, x, key[0], row.dst) for e, x in zip(r_eid, r_end, strict=True) if x != row.dst]
                    c_eid.append(row.eid), c_end.append(row.dst)
        state.update((r_eid, r_end, c_eid, c_end))
        state.setTimeoutTimestamp(max(latest, state.getCurrentWatermarkMs()) + millis)
        yield pd.DataFrame(out, columns=["eid_rare", "eid_common", "a", "b", "c"])

    kinds = "r_eid array<long>, r_end array<long>, c_eid array<long>, c_end array<long>"
    return rows.groupBy("b").applyInPandasWithState(step, "eid_rare long, eid_common long, a long, b long, c long", kinds, "append", "EventTimeTimeout")


def live_histogram(source: DataFrame, window: str, slide: str | None = None, watermark: str = "1 day", session: bool = False) -> DataFrame:
    """Edges of each kind in windows of time: tumbling, sliding, or sessions that end after ``window`` without an edge."""
    span = F.session_window("ts", window) if session else F.window("ts", window, slide)
    return source.withWatermark("ts", watermark).groupBy(span, "etype").agg(F.count("*").alias("n"))


def first_seen(source: DataFrame, watermark: str) -> DataFrame:
    """Edges that were not yet seen within the watermark, by eid: a feed that repeats itself comes out once."""
    return source.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["eid"])

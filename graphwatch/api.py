"""One call from edges and a pattern to matches."""

from __future__ import annotations

from pyspark.sql import DataFrame

from graphwatch.model import QueryGraph
from graphwatch.operators.matching import run_tree
from graphwatch.plans.cutting import THRESHOLD, choose_strategy, collect_statistics


def watch(edges: DataFrame, graph: QueryGraph, strategy: str = "auto", threshold: float = THRESHOLD, prefix: int | None = 100_000, within: str | None = None, **settings) -> DataFrame:
    """All matches, under the strategy that statistics of the first edges choose (auto) or a named one: eager1, gated1, eager2, gated2."""
    known = collect_statistics(edges, prefix)
    choice = choose_strategy(graph, known, threshold, strategy)
    return run_tree(edges, choice.tree, graph, gated=choice.strategy.startswith("gated"), within=within, **settings)

"""python -m graphwatch plan EDGES "a -k4> b; b -k0> c" PLAN | run EDGES PLAN OUT: edges and results are Parquet, plans are JSON."""

from __future__ import annotations

import sys

from pyspark.sql import SparkSession

from graphwatch.model import pattern
from graphwatch.operators.matching import run_tree
from graphwatch.plans import cutting
from graphwatch.sources.graphs import read_edges


def main(args: list[str]) -> int:
    if len(args) != 4 or args[0] not in ("plan", "run"):
        sys.exit(__doc__)
    spark = SparkSession.builder.getOrCreate()
    edges = read_edges(spark, args[1])
    if args[0] == "plan":
        graph = pattern(*[x.strip() for x in args[2].split(";")])
        known = cutting.collect_statistics(edges, 100_000)
        choice = cutting.choose_strategy(graph, known)
        cutting.save_plan(choice.tree, graph, args[3])
        print(choice.strategy, choice.log10_xi)
        print(cutting.explain_tree(choice.tree, known))
    else:
        tree, graph = cutting.load_plan(args[2])
        run_tree(edges, tree, graph, gated=True).write.mode("overwrite").parquet(args[3])
    return 0


if __name__ == "__main__":
    sys.exit(main(sys.argv[1:]))

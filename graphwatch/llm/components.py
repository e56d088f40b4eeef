"""Connected components of an edge table, without collecting edges."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphwatch.functions.storage import table


def _with_least(pairs: DataFrame) -> DataFrame:
    """pairs (u, v) with ``m``, the least of u and its v's. The least comes from partial sums and is joined back, so a hub's rows can be split over tasks."""
    least = table(pairs.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("_u"), F.least("u", "m").alias("m")), "cc-least")
    return pairs.join(least, F.col("u") == F.col("_u")).drop("_u")


def connected_components(edges: DataFrame) -> DataFrame:
    """edges (a, b) -> id, component (the least id that can be reached), for every id that has an edge.

    Large-star and small-star rounds until the edges stay the same; each round writes its edges to
    the shared folder. Loops and repeated edges do no harm; no edges give an empty table.
    """
    now = table(edges.filter("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "cc-edges")
    mark = None
    while True:
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = _with_least(table(both, "cc-both")).filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").distinct()
        small = _with_least(table(large, "cc-large"))
        small = small.select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.*")
        now = table(small.filter("u <> v").distinct(), "cc-edges")
        seen = now.agg(F.count("*").alias("n"), F.coalesce(F.bit_xor(F.xxhash64("u", "v")), F.lit(0)).alias("x")).first()
        if mark == (seen.n, seen.x):
            break
        mark = (seen.n, seen.x)
    roots = now.select(F.col("v").alias("id"), F.col("v").alias("component")).distinct()
    return now.select(F.col("u").alias("id"), F.col("v").alias("component")).unionByName(roots)

"""Global ranks and running sums without a window over one partition."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphwatch.functions.storage import cut, passing_table


def range_sums(df: DataFrame, order: list[Column], sums: dict[str, Column], by: str | None = None, partitions: int | None = None) -> DataFrame:
    """Add, for each name in ``sums``, the sum of its column over all rows before this one in ``order``, within ``by``.

    ``order`` must begin with ``by`` if that is given, and should leave no ties. Rows are
    range-partitioned, so that a hot group is spread over many tasks; only one row for each
    partition (and group in it) meets in the window that adds the offsets up. The sorted rows are
    checkpointed, since sums and offsets must see the same partitions.
    """
    dealt = df.repartitionByRange(partitions, *order) if partitions else df.repartitionByRange(*order)
    group = [F.col(by)] if by else []
    within = Window.partitionBy("_part", *group).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    rows = dealt.withColumn("_part", F.spark_partition_id())
    rows = rows.withColumns({f"_w_{k}": c.cast("long") for k, c in sums.items()})
    rows = cut(rows.withColumns({f"_l_{k}": F.coalesce(F.sum(f"_w_{k}").over(within), F.lit(0)) for k in sums}))
    totals = rows.groupBy("_part", *group).agg(*[F.sum(f"_w_{k}").alias(f"_s_{k}") for k in sums])
    before = Window.partitionBy(*(group or [F.lit(0)])).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = totals.select(F.col("_part").alias("_p"), *([F.col(by).alias("_b")] if by else []), *[F.coalesce(F.sum(f"_s_{k}").over(before), F.lit(0)).alias(f"_o_{k}") for k in sums])
    on = F.col("_part") == F.col("_p")
    joined = rows.join(offsets, on & F.col(by).eqNullSafe(F.col("_b")) if by else on, "left")
    return joined.select(*df.columns, *[(F.col(f"_l_{k}") + F.coalesce(F.col(f"_o_{k}"), F.lit(0))).alias(k) for k in sums])


def range_rank(df: DataFrame, order: list[Column], out: str, by: str | None = None) -> DataFrame:
    """Add ``out``, the place of the row in ``order`` (within ``by``), from 0."""
    return range_sums(df, order, {out: F.lit(1)}, by)


def stored_rank(df: DataFrame, order: list[Column], out: str, name: str) -> DataFrame:
    """df with ``out``, the place of the row in ``order`` from 0, as a passing table: columns and kinds of rows are read apart.

    The offsets, one number for each partition, are worked out once and stand in the plan.
    """
    within = Window.partitionBy("_part").orderBy(*order)
    rows = df.repartitionByRange(*order).withColumn("_part", F.spark_partition_id())
    rows = passing_table(rows.withColumn("_at", F.row_number().over(within)), name)
    sizes = {r["_part"]: r["count"] for r in rows.groupBy("_part").count().collect()}
    offsets, before = [], -1
    for part in range(max(sizes, default=0) + 1):
        offsets.append(f"{before}L")
        before += sizes.get(part, 0)
    return rows.select(*df.columns, (F.col("_at") + F.expr(f"array({', '.join(offsets)})")[F.col("_part")]).alias(out))

"""User-defined functions around the methods; none of the methods needs one."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType, LongType, StringType, StructField, StructType


def user_kind(rule) -> Callable[[Column], Column]:
    """A kind map of the user's own, on whole columns: with_kind(edges, user_kind(rule)(col))."""
    return pandas_udf(rule, StringType())


@pandas_udf(DoubleType())
def gini(counts: pd.Series) -> float:
    """How uneven counts are: 0 if all are equal, near 1 if one has nearly all."""
    x = counts.sort_values().to_numpy(dtype=float)
    n, total = len(x), x.sum()
    return 0.0 if total == 0 else float(((2 * pd.Series(range(1, n + 1)) - n - 1) * x).sum() / (n * total))


@udtf(returnType=StructType([StructField("v", LongType()), StructField("sig", StringType())]))
class Incident:
    """Both ends of an edge, with direction and kind, as a table function for SQL."""

    def eval(self, src: int, dst: int, etype: str) -> Iterator[tuple[int, str]]:
        yield src, f"o:{etype}"
        yield dst, f"i:{etype}"


def register(spark) -> None:
    """Make the table function known to SQL as incident(src, dst, etype)."""
    spark.udtf.register("incident", Incident)


def band_of(cuts: tuple[float, ...]) -> Callable[[Column], Column]:
    """Value bands as a user's rule, like the built-in band_kind."""

    def rule(x: pd.Series) -> pd.Series:
        return "k" + pd.Series(pd.cut(x, [float("-inf"), *cuts, float("inf")], right=False, labels=False), index=x.index).astype(int).astype(str)

    return user_kind(rule)


"""Joins around the methods: intervals without a nested loop, and as-of."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def interval_join(left: DataFrame, right: DataFrame, keys: list[str], at: str, start: str, width: int, after: bool = True) -> DataFrame:
    """Rows of `left` whose `at` lies in (start, start + width] of a row of `right` with the same keys.

    Both sides get buckets of the interval's width; a right row covers at most two of them, so the
    join is an equi-join on keys and bucket, with the interval as residual.
    """
    l = left.withColumn("__b", F.floor(F.col(at) / F.lit(width)))  # noqa: E741
    r = right.withColumn("__b", F.explode(F.array_distinct(F.array(F.floor(F.col(start) / F.lit(width)), F.floor((F.col(start) + width) / F.lit(width))))))
    return l.join(r, [*keys, "__b"]).where((F.col(at) > F.col(start)) & (F.col(at) <= F.col(start) + width)).drop("__b")


def as_of(left: DataFrame, right: DataFrame, keys: list[str], at: str, value: Column, name: str, strict: bool = True) -> DataFrame:
    """Each left row with the value of the last right row of its keys before it (or at it, if not strict).

    One union and one window per key: a single shuffle, no range comparison of the two sides.
    """
    l = left.withColumn("__v", F.lit(None)).withColumn("__side", F.lit(1))  # noqa: E741
    r = right.select(*keys, at, value.alias("__v")).withColumn("__side", F.lit(0))
    both = r.unionByName(l, allowMissingColumns=True)
    w = Window.partitionBy(*keys).orderBy(at)
    frame = w.rangeBetween(Window.unboundedPreceding, -1) if strict else w.rangeBetween(Window.unboundedPreceding, 0)
    return both.withColumn(name, F.last("__v", True).over(frame)).where("__side = 1").drop("__v", "__side")

"""Joins over time: the latest earlier row, and ranges by buckets."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def as_of_join(left: DataFrame, right: DataFrame, by: list[str], time: str, value: str, alias: str | None = None) -> DataFrame:
    """left with the latest ``value`` of right at or before each row's time, within equal ``by``; NULL where there is none.

    Both sides go through one sort by key and time, with no comparison of pairs.
    Several right rows of the same time count by their greatest value.
    """
    alias = alias or value
    right = right.groupBy(*by, time).agg(F.max(value).alias("__v"))
    both = left.select("*", F.lit(1).alias("__left"), F.lit(None).cast(right.schema["__v"].dataType).alias("__v")).unionByName(right.select(*by, time, "__v", F.lit(0).alias("__left")), allowMissingColumns=True)
    w = Window.partitionBy(*by).orderBy(time, "__left").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return both.withColumn(alias, F.last("__v", ignorenulls=True).over(w)).where("__left = 1").drop("__left", "__v")


def range_join(points: DataFrame, ranges: DataFrame, by: list[str], at: str, start: str, end: str, width: int) -> DataFrame:
    """Points with every range of the same key that holds them (ends included): an equi-join on buckets of ``width``.

    A range is repeated once for each bucket it touches, so width should be near
    the usual length of a range.
    """
    number = lambda c: F.floor(F.col(c).cast("double") / width)
    p = points.withColumn("__b", number(at))
    r = ranges.withColumn("__b", F.explode(F.sequence(number(start), number(end))))
    return p.join(r, [*by, "__b"]).where(F.col(at).between(F.col(start), F.col(end))).drop("__b")

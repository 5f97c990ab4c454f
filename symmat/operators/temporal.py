"""Joins of points with intervals and of events with the latest earlier state, as equi-joins and windows: no nested loops."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def interval_join(points: DataFrame, intervals: DataFrame, by: list[str], at: str, start: str, end: str, width: float) -> DataFrame:
    """Each point with every interval of its keys that holds it, start <= at < end.

    Time (or position) is cut into pieces of ``width``; an interval is filed under each piece it touches, a point under its
    own, and the two meet by equality of keys and piece. Columns other than ``by`` must have different names.
    """
    piece = F.floor(F.col(at) / F.lit(width))
    first, last = F.floor(F.col(start) / F.lit(width)), F.floor(F.col(end) / F.lit(width))
    filed = intervals.where(F.col(start) < F.col(end)).withColumn("__piece", F.explode(F.sequence(first, last)))
    met = points.withColumn("__piece", piece).join(filed, [*by, "__piece"])
    return met.where((F.col(at) >= F.col(start)) & (F.col(at) < F.col(end))).drop("__piece")


def as_of(left: DataFrame, right: DataFrame, by: list[str], at: str, value: str) -> DataFrame:
    """``left`` with ``value`` of the latest row of ``right`` (by..., at, value) not after it; null where there is none.

    One sort of both sides together by key and time; of rows of ``right`` at one time, the largest value counts.
    """
    names = [c for c in left.columns if c not in (*by, at)]
    nothing = [F.lit(None).cast(t).alias(c) for c, t in left.dtypes if c in names]
    kind = dict(right.dtypes)[value]
    state = right.select(*by, at, F.col(value).alias("__v"), F.lit(0).alias("__kind"), *nothing)
    asked = left.select(*by, at, F.lit(None).cast(kind).alias("__v"), F.lit(1).alias("__kind"), *names)
    order = Window.partitionBy(*by).orderBy(at, "__kind", "__v").rowsBetween(Window.unboundedPreceding, 0)
    return state.union(asked).withColumn(value, F.last("__v", ignorenulls=True).over(order)).where("__kind = 1").select(*left.columns, value)

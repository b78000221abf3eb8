"""Joins by order that Spark has no operator for: as-of and interval joins."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, key: str, at: str, values: list[str]) -> DataFrame:
    """``left`` with ``values`` of the row of ``right`` of the same key that is the last at or before ``at`` (null if none).

    Both sides are sorted together and the last right row is carried forward: one exchange by key, no pairs.  Of right
    rows with equal ``at`` the one with the largest values counts.
    """
    carried = F.struct(*[F.col(v).alias(v) for v in values])
    names = left.columns
    rows = left.select(F.col(key).alias("__key"), F.col(at).alias("__at"), F.lit(1).alias("__side"), F.struct(*names).alias("__left"), F.lit(None).cast(right.select(carried.alias("x")).schema["x"].dataType).alias("__right"))
    told = right.select(F.col(key).alias("__key"), F.col(at).alias("__at"), F.lit(0).alias("__side"), F.lit(None).cast(rows.schema["__left"].dataType).alias("__left"), carried.alias("__right"))
    before = Window.partitionBy("__key").orderBy("__at", "__side", "__right").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    out = rows.union(told).withColumn("__last", F.last("__right", ignorenulls=True).over(before)).where("__side = 1")
    return out.select(*[F.col(f"__left.{c}").alias(c) for c in names], *[F.col(f"__last.{v}").alias(v) for v in values])


def interval_join(points: DataFrame, spans: DataFrame, at: str, low: str, high: str, width: int) -> DataFrame:
    """Pairs of points and spans with low <= at < high, by an equality join of buckets of ``width``.

    A span is copied to the buckets it crosses (pick a width like that of most spans); a point looks into one bucket.
    Spans without room or with a null end have no pairs.  ``at``, ``low`` and ``high`` are whole numbers.
    """
    bucket = lambda c: F.floor(c / F.lit(width))
    crossed: Column = F.sequence(bucket(F.col(low)), bucket(F.col(high) - 1))
    copied = spans.where(F.col(low) < F.col(high)).withColumn("__bucket", F.explode(crossed))
    return points.withColumn("__bucket", bucket(F.col(at))).join(copied, "__bucket").where((F.col(low) <= F.col(at)) & (F.col(at) < F.col(high))).drop("__bucket")

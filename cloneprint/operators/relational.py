"""Joins and summaries that Spark has no single operator for."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, *values: str) -> DataFrame:
    """Each left row with the values of the latest right row of its key at or before it.

    Both sides are stacked and sorted once per key; the last right row is carried forward. No row meets more than its own key.
    """
    carry = F.struct(right_time, *values)
    l_cols = [c for c in left.columns if c != key]
    a = left.select(key, F.col(left_time).alias("_t"), F.lit(1).alias("_side"), F.struct(*l_cols).alias("_l"), F.lit(None).cast(right.select(carry.alias("x")).schema["x"].dataType).alias("_r"))
    b = right.select(key, F.col(right_time).alias("_t"), F.lit(0).alias("_side"), F.lit(None).cast(a.schema["_l"].dataType).alias("_l"), carry.alias("_r"))
    w = Window.partitionBy(key).orderBy("_t", "_side").rowsBetween(Window.unboundedPreceding, 0)
    out = a.unionByName(b).withColumn("_r", F.last("_r", ignorenulls=True).over(w)).where("_side = 1")
    return out.select(key, *[F.col(f"_l.{c}").alias(c) for c in l_cols], *[F.col(f"_r.{c}").alias(c) for c in (right_time, *values)])


def range_join(points: DataFrame, ranges: DataFrame, point: str, start: str, end: str, width: int) -> DataFrame:
    """Points inside [start, end) of numeric ranges: an equi-join on buckets of ``width``, then the exact test."""
    p = points.withColumn("_b", F.floor(F.col(point) / width))
    r = ranges.withColumn("_b", F.explode(F.sequence(F.floor(F.col(start) / width), F.floor((F.col(end) - 1) / width)))).where(F.col(end) > F.col(start))
    return p.join(r, "_b").where((F.col(point) >= F.col(start)) & (F.col(point) < F.col(end))).drop("_b")


def top_k(df: DataFrame, group: str, order: list[Column], k: int) -> DataFrame:
    return df.withColumn("place", F.row_number().over(Window.partitionBy(group).orderBy(*order))).where(F.col("place") <= k)

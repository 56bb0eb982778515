"""Joins and aggregations that Spark has no operator for, from those it has."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def range_join(points: DataFrame, ranges: DataFrame, value: str, low: str, high: str, width: float) -> DataFrame:
    """Points within ranges, as an equality join on bins of the given width: a range goes to each bin that it touches."""
    p = points.withColumn("_bin", F.floor(F.col(value) / width))
    r = ranges.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    return p.join(r, "_bin").where(F.col(value).between(F.col(low), F.col(high))).drop("_bin")


def asof_join(left: DataFrame, right: DataFrame, keys: list[str], time: str, value: str) -> DataFrame:
    """The last right value at or before each left row's time, by key; one sort of both sides, no pairs."""
    marked = left.withColumn("_side", F.lit(1)).withColumn(value, F.lit(None).cast(right.schema[value].dataType))
    extra = [c for c in left.columns if c not in (*keys, time)]
    other = right.select(*keys, time, *[F.lit(None).cast(left.schema[c].dataType).alias(c) for c in extra], F.lit(0).alias("_side"), value)
    w = Window.partitionBy(*keys).orderBy(time, "_side", value).rowsBetween(Window.unboundedPreceding, 0)
    both = marked.select(*keys, time, *extra, "_side", value).unionAll(other)
    return both.withColumn(value, F.last(value, ignorenulls=True).over(w)).where("_side = 1").drop("_side")


def salted_join(big: DataFrame, small: DataFrame, on: list[str], salts: int) -> DataFrame:
    """Join with each key of the big side dealt to several tasks, and the small side sent to all of them."""
    left = big.withColumn("_salt", F.pmod(F.xxhash64(*big.columns), F.lit(salts)))
    right = small.withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(salts - 1).cast("bigint"))))
    return left.join(right, [*on, "_salt"]).drop("_salt")


def salted_group(df: DataFrame, keys: list[str], partial: list[Column], final: list[Column], salts: int = 16) -> DataFrame:
    """Aggregation in two steps, first by key and salt; for aggregates without map-side combination."""
    return df.withColumn("_salt", F.pmod(F.xxhash64(*df.columns), F.lit(salts))).groupBy(*keys, "_salt").agg(*partial).groupBy(*keys).agg(*final)

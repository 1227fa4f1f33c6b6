"""Joins that Spark has no operator for."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def as_of(left: DataFrame, right: DataFrame, keys: list[str], order: list[str], value: str) -> DataFrame:
    """left with the value of the last right row of its keys that comes strictly before it in `order`; one sort, no range join."""
    both = left.withColumns({"_side": F.lit(1), value: F.lit(None).cast(right.schema[value].dataType)}).unionByName(right.select(*keys, *order, value).withColumn("_side", F.lit(0)), allowMissingColumns=True)
    before = Window.partitionBy(*keys).orderBy(*order, F.desc("_side")).rowsBetween(Window.unboundedPreceding, -1)
    return both.withColumn(value, F.last(value, ignorenulls=True).over(before)).where("_side = 1").drop("_side")


def interval_join(left: DataFrame, right: DataFrame, keys: list[str], left_time: str, right_time: str, seconds: int) -> DataFrame:
    """Rows of equal keys whose times differ by at most `seconds`: an equi-join on time buckets, each right row in three of them."""
    bucket = lambda c: F.floor(F.unix_micros(F.col(c).cast("timestamp")) / (seconds * 1_000_000))
    near = right.withColumn("_bucket", F.explode(F.array(*[bucket(right_time) + d for d in (-1, 0, 1)])))
    gap = F.abs(F.unix_micros(F.col(left_time).cast("timestamp")) - F.unix_micros(F.col(right_time).cast("timestamp")))
    return left.withColumn("_bucket", bucket(left_time)).join(near, [*keys, "_bucket"]).where(gap <= seconds * 1_000_000).drop("_bucket")

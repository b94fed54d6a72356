"""Joins around the miners: as-of, range and array-overlap joins without nested loops."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def join_asof(left: DataFrame, right: DataFrame, on: str, by: str, value: str) -> DataFrame:
    """Each left row with the right side's latest `value` at or before it: one union, one window, no join."""
    one = left.select(F.struct("*").alias("l"), F.col(by).alias("by"), F.col(on).alias("at"), F.lit(1).alias("side"), F.lit(None).cast(right.schema[value].dataType).alias("v"))
    two = right.select(F.lit(None).cast(one.schema["l"].dataType).alias("l"), F.col(by).alias("by"), F.col(on).alias("at"), F.lit(0).alias("side"), F.col(value).alias("v"))
    order = Window.partitionBy("by").orderBy("at", "side", "v").rowsBetween(Window.unboundedPreceding, 0)
    return one.unionByName(two).withColumn("v", F.last("v", ignorenulls=True).over(order)).where("side = 1").select("l.*", F.col("v").alias(f"asof_{value}"))


def join_range(left: DataFrame, right: DataFrame, at: str, low: str, high: str, by: str, bucket_seconds: int) -> DataFrame:
    """Rows of left whose `at` lies in [low, high] of a right row with the same key: equi-join on time buckets."""
    step = F.lit(bucket_seconds)
    bucket = lambda c: F.floor(F.unix_seconds(F.col(c).cast("timestamp")) / step)
    one = left.withColumn("_b", bucket(at))
    two = right.withColumn("_b", F.explode(F.sequence(bucket(low), bucket(high))))
    return one.join(two, [by, "_b"]).where(F.col(at).between(F.col(low), F.col(high))).drop("_b")


def join_overlap(df: DataFrame, other: DataFrame, key: str, array: str, other_key: str, other_array: str) -> DataFrame:
    """Distinct pairs of keys whose arrays share an element."""
    one = df.select(F.col(key).alias("k1"), F.explode(F.array_distinct(array)).alias("_e"))
    two = other.select(F.col(other_key).alias("k2"), F.explode(F.array_distinct(other_array)).alias("_e"))
    return one.join(two, "_e").select("k1", "k2").distinct()

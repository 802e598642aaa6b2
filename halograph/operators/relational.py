"""Relational operators a user of the methods needs beside them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from halograph.functions.ring import whole


def minimum_image(d: Column, length: int) -> Column:
    """Displacement to the nearest periodic image."""
    return F.when(d * 2 > length, d - length).when(d * 2 < -length, d + length).otherwise(d)


def as_of(left: DataFrame, right: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """left with the last value of right at or before its time, by one sort of both: no product however many match."""
    a = left.select(key, time, F.lit(None).cast(dict(right.dtypes)[value]).alias(value), F.lit(1).alias("_side"))
    b = right.select(key, time, value, F.lit(0).alias("_side"))
    w = Window.partitionBy(key).orderBy(time, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b).withColumn(value, F.last(value, ignorenulls=True).over(w)).filter("_side = 1").drop("_side")


def range_join(points: DataFrame, intervals: DataFrame, x: str, low: str, high: str, width: int) -> DataFrame:
    """Pairs with low <= x < high, met by bins of the given width instead of comparing all."""
    bins = intervals.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor((F.col(high) - 1) / width))))
    return points.withColumn("_bin", F.floor(F.col(x) / width)).join(bins, "_bin").filter((F.col(x) >= F.col(low)) & (F.col(x) < F.col(high))).drop("_bin")


def nearest(edges: DataFrame, k: int) -> DataFrame:
    """The k nearest neighbours of each atom; ties by source and image."""
    w = Window.partitionBy("dst").orderBy("d2", "src", "ix", "iy", "iz")
    return edges.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


def salted_sum(df: DataFrame, key: str, value: str, salts: int = 16) -> DataFrame:
    """Sum by key in two steps, for keys that hold a large share of all rows."""
    part = df.withColumn("_salt", F.pmod(F.xxhash64(*df.columns), F.lit(salts))).groupBy(key, "_salt").agg(F.sum(value).alias("_part"))
    return part.groupBy(key).agg(F.sum("_part").alias(value))


def frames(events: DataFrame, seconds: int) -> DataFrame:
    """Events counted and summed in windows of fixed length, by whole seconds since the epoch."""
    at = F.unix_seconds(F.col("ts").cast("timestamp"))
    return events.groupBy(whole(at, seconds).alias("frame"), "event_type").agg(F.count(F.lit(1)).alias("events"), F.countDistinct("user_id").alias("users"))


def sessions(events: DataFrame, gap_seconds: int) -> DataFrame:
    """Sessions of users: runs of events with no gap of that length."""
    at = F.unix_seconds(F.col("ts").cast("timestamp"))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    cut = F.when(at - F.lag(at).over(w) < gap_seconds, 0).otherwise(1)
    numbered = events.withColumn("_cut", cut).withColumn("session", F.sum("_cut").over(w))
    return numbered.groupBy("user_id", "session").agg(F.count(F.lit(1)).alias("events"), F.min(at).alias("first"), F.max(at).alias("last"))

"""Sinks: Parquet by partition, bucketed tables, JSON and CSV reports."""

from __future__ import annotations

from pyspark.sql import DataFrame


def by_part(df: DataFrame, path: str) -> None:
    """One folder for each part, so a reader of a part opens its files only."""
    df.repartition("part_id").write.mode("overwrite").partitionBy("part_id").parquet(path)


def bucketed(df: DataFrame, table: str, buckets: int, *keys: str) -> None:
    """A table whose joins and aggregates on the keys need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, *keys).sortBy(*keys).saveAsTable(table)


def report(df: DataFrame, path: str, kind: str = "json") -> None:
    writer = df.coalesce(1).write.mode("overwrite")
    writer.option("header", True).csv(path) if kind == "csv" else writer.json(path)

"""Connected components of a table of links, without gathering links or components anywhere."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from halograph.llm.common import Scratch


def _print(edges: DataFrame) -> tuple:
    """Count and sum of hashes: two numbers that tell whether a round changed anything."""
    return tuple(edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("v", "u").cast("decimal(38,0)"))).first())


def components(links: DataFrame, scratch: Scratch) -> DataFrame:
    """node, component for every node of links (a, b): the smallest node that can be reached.

    Stars are contracted by turns (large star, small star) until a round changes nothing, so the number of rounds grows
    with the logarithm of the longest path. Each step groups node identifiers once.
    """
    edges = scratch.keep(links.select(F.greatest("a", "b").alias("v"), F.least("a", "b").alias("u")).filter("u < v").distinct(), "edges")
    before = _print(edges)
    while before[0]:
        # large star: every larger neighbour points at the least of the neighbourhood
        both = edges.select(F.col("u").alias("x"), F.col("v").alias("y")).union(edges.select(F.col("v").alias("x"), F.col("u").alias("y")))
        least = F.least(F.min("y").over(Window.partitionBy("x")), F.col("x"))
        large = both.withColumn("u", least).filter("y > x").select(F.col("y").alias("v"), "u").filter("u < v").distinct()
        large = scratch.keep(large, "large")
        # small star: a node and its smaller neighbours point at the least of these
        held = large.withColumn("m", F.min("u").over(Window.partitionBy("v")))
        small = held.select(F.when(F.col("u") == F.col("m"), F.col("v")).otherwise(F.col("u")).alias("v"), F.col("m").alias("u")).distinct()
        edges = scratch.keep(small, "small")
        after = _print(edges)
        if after == before and _print(large) == before:
            break
        before = after
    roots = edges.select(F.col("u").alias("node")).distinct().withColumn("component", F.col("node"))
    return edges.select(F.col("v").alias("node"), F.col("u").alias("component")).union(roots)

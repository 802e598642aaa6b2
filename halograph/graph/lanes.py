"""The layout in which layers run: each part in a lane of its own, all tables of a graph bucketed by lane.

A lane is a number whose hash falls into the bucket of its part, so a part is one bucket of every table, joins and sums
inside a part need no exchange, and only what is sent to another lane is shuffled.
"""

from __future__ import annotations

from contextlib import contextmanager
from dataclasses import dataclass
from functools import lru_cache

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from halograph.graph.scratch import Scratch

_MASK = 0xFFFFFFFF


def _turned(x: int, r: int) -> int:
    return ((x << r) | (x >> (32 - r))) & _MASK


def bucket_hash(value: int) -> int:
    """Spark's bucket hash of an int: Murmur 3 with seed 42."""
    k = _turned((value & _MASK) * 0xCC9E2D51 & _MASK, 15) * 0x1B873593 & _MASK
    h = (_turned(42 ^ k, 13) * 5 + 0xE6546B64) & _MASK
    h ^= 4
    h = (h ^ (h >> 16)) * 0x85EBCA6B & _MASK
    h = (h ^ (h >> 13)) * 0xC2B2AE35 & _MASK
    h ^= h >> 16
    return h - (1 << 32) if h >> 31 else h


@lru_cache(maxsize=16)
def lane_keys(p: int) -> tuple[int, ...]:
    """For each part the smallest number that falls into its bucket of p."""
    found: dict[int, int] = {}
    value = 0
    while len(found) < p:
        found.setdefault(bucket_hash(value) % p, value)
        value += 1
    return tuple(found[i] for i in range(p))


@dataclass(frozen=True)
class Lanes:
    p: int
    scratch: Scratch

    def lane(self, part: Column) -> Column:
        keys = lane_keys(self.p)
        return F.lit(keys[0]) if self.p == 1 else F.element_at(F.array(*[F.lit(k) for k in keys]), part + 1)

    def dealt(self, df: DataFrame) -> DataFrame:
        """Moves rows to their lanes: the one kind of shuffle that layers make."""
        return df.repartition(self.p, "lane")

    def keep(self, df: DataFrame, name: str) -> DataFrame:
        """Writes a table whose rows lie in their lanes; reading it back keeps them there."""
        with within_lanes(df.sparkSession):
            return self.scratch.keep_bucketed(df, name, "lane", self.p)


@contextmanager
def within_lanes(spark):
    """Lets joins on the lane and more columns stay in the lane; Spark otherwise deals both sides anew by all columns."""
    name = "spark.sql.requireAllClusterKeysForCoPartition"
    before = spark.conf.get(name)
    spark.conf.set(name, "false")
    try:
        yield
    finally:
        spark.conf.set(name, before)

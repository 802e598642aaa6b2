"""Text files of particle systems: a count, a comment with the cell, and a line for each atom."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from halograph.sources.systems import System

SCHEMA = "atom_id long, species int, x long, y long, z long"


class _Shard(InputPartition):
    def __init__(self, path: str):
        self.path = path


class XyzReader(DataSourceReader):
    def __init__(self, paths: list[str]):
        self.paths = paths

    def partitions(self):
        return [_Shard(p) for p in self.paths]

    def read(self, partition):
        with open(partition.path, encoding="utf-8") as f:
            n = int(f.readline())
            f.readline()
            for _ in range(n):
                atom, species, x, y, z = f.readline().split()
                yield int(atom), int(species), int(x), int(y), int(z)


class XyzSource(DataSource):
    """format("particles"): option paths is a list separated by commas; each file is one partition."""

    @classmethod
    def name(cls):
        return "particles"

    def schema(self):
        return SCHEMA

    def reader(self, schema):
        return XyzReader(self.options["paths"].split(","))


def read(spark: SparkSession, *paths: str) -> DataFrame:
    spark.dataSource.register(XyzSource)
    return spark.read.format("particles").option("paths", ",".join(paths)).load()


def write(system: System, path: str) -> None:
    """Writes a system of any size as text rows (id species x y z) by the parallel text sink."""
    rows = system.atoms.select(F.concat_ws(" ", "atom_id", "species", "x", "y", "z").alias("value"))
    rows.write.mode("overwrite").text(path)


def read_rows(spark: SparkSession, path: str) -> DataFrame:
    """Reads what write has written, through Spark's own reader, from any store."""
    part = F.split("value", " ")
    types = [t.split() for t in SCHEMA.split(", ")]
    return spark.read.text(path).select(*[part[k].cast(t).alias(n) for k, (n, t) in enumerate(types)])

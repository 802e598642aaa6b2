"""Tables written to the shared folder of spark.checkpoint.dir: they cut lineage and outlive lost executors."""

from __future__ import annotations

import atexit
import os
import sys
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_live: list["Scratch"] = []


def shared_folder(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir. Only a session of one machine, as in tests, may leave it unset."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
    return os.path.join(tempfile.gettempdir(), "checkpoints")


class Scratch:
    """The written tables of one call. They stay until ``drop`` or the end of the program, for lazy results read them."""

    def __init__(self, spark: SparkSession):
        self.spark, self.n, self.tables, self.shared = spark, 0, [], {}
        self.root = f"{shared_folder(spark)}/halograph-{uuid.uuid4().hex}"
        _live.append(self)

    def path(self, name: str) -> str:
        self.n += 1
        return f"{self.root}/{self.n:03d}-{name}"

    def keep(self, df: DataFrame, name: str, **options: str) -> DataFrame:
        """Writes df as Parquet and returns the table that reads it."""
        path = self.path(name)
        df.write.options(**options).parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def keep_bucketed(self, df: DataFrame, name: str, key: str, buckets: int | None = None) -> DataFrame:
        """As keep, in buckets of the key: later joins on the key leave this table where it is."""
        buckets = buckets or max(8, int(self.spark.conf.get("spark.sql.shuffle.partitions")))
        path, table = self.path(name), f"halograph_{uuid.uuid4().hex}"
        self.tables.append(table)
        df.write.bucketBy(buckets, key).option("path", path).saveAsTable(table)
        return self.spark.table(table)

    def drop(self) -> None:
        """Removes folder and table names; results that still read them can no longer be computed."""
        try:
            for t in self.tables:
                self.spark.sql(f"DROP TABLE IF EXISTS {t}")
            p = self.spark._jvm.org.apache.hadoop.fs.Path(self.root)
            p.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(p, True)
        except Exception as e:  # the session may be gone already; a leftover folder is all that remains
            print(f"scratch folder {self.root} was left: {type(e).__name__}", file=sys.stderr)
        if self in _live:
            _live.remove(self)


@atexit.register
def _at_exit() -> None:
    """Removes what is left, on a shared store through the session as long as it runs."""
    for s in list(_live):
        if getattr(s.spark.sparkContext, "_jsc", None) is not None:
            s.drop()
        elif os.path.isdir(s.root):
            import shutil

            shutil.rmtree(s.root, ignore_errors=True)

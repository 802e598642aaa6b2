"""Trajectories as streams: frames and sessions of events with watermarks, and a stateful skin tracker."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from contextlib import contextmanager

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

_EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, folder: str) -> DataFrame:
    """Events of a Parquet file or folder as they arrive, with ``at`` as event time.

    The path is given as a pattern: a stream takes a lone file only so.
    """
    return spark.readStream.schema(_EVENTS).parquet(f"{folder[:-1]}[{folder[-1]}]").withColumn("at", F.col("ts").cast("timestamp"))


def tumbling_frames(stream: DataFrame, width: str = "1 hour", late: str = "1 hour") -> DataFrame:
    framed = stream.withWatermark("at", late).groupBy(F.window("at", width).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("events"), F.max("user_id").alias("most_user"))
    return framed.select(F.unix_seconds("w.start").alias("frame_start"), "event_type", "events", "most_user")


def sliding_frames(stream: DataFrame, width: str = "2 hours", slide: str = "1 hour", late: str = "1 hour") -> DataFrame:
    framed = stream.withWatermark("at", late).groupBy(F.window("at", width, slide).alias("w")).agg(F.count(F.lit(1)).alias("events"))
    return framed.select(F.unix_seconds("w.start").alias("frame_start"), "events")


def session_frames(stream: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    s = stream.withWatermark("at", late).groupBy(F.session_window("at", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("events"))
    return s.select("user_id", F.unix_seconds("w.start").alias("first"), (F.unix_seconds("w.end")).alias("ends"), "events")


def without_repeats(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("at", late).dropDuplicatesWithinWatermark(["event_id"])


def with_users(stream: DataFrame, users: DataFrame) -> DataFrame:
    """Stream-static join: each event with the fixed row of its user."""
    return stream.join(users, "user_id")


def within(left: DataFrame, right: DataFrame, minutes: int, late: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: right events of the same user at most so many minutes after a left one."""
    a = left.withWatermark("at", late).select(F.col("user_id").alias("a_user"), F.col("event_id").alias("a_id"), F.col("at").alias("a_at"))
    b = right.withWatermark("at", late).select(F.col("user_id").alias("b_user"), F.col("event_id").alias("b_id"), F.col("at").alias("b_at"))
    return a.join(b, F.expr(f"a_user = b_user AND b_at >= a_at AND b_at <= a_at + INTERVAL {minutes} MINUTES"))


class SkinTracker(StatefulProcessor):
    """Per atom: the displacement since the last rebuild; a row comes out when it passes half the skin."""

    HALF_SKIN = 100.0

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.moved = handle.getValueState("moved", "total double, rebuilds int")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        total, rebuilds = self.moved.get() if self.moved.exists() else (0.0, 0)
        out = []
        for batch in rows:
            for v in batch.sort_values("event_id")["value"].fillna(0.0):
                total += abs(float(v))
                if total > self.HALF_SKIN:
                    total, rebuilds = 0.0, rebuilds + 1
                    out.append((key[0], rebuilds))
        self.moved.update((total, rebuilds))
        yield pd.DataFrame(out, columns=["user_id", "rebuild"])

    def close(self) -> None:
        pass


def skin_rebuilds(stream: DataFrame) -> DataFrame:
    return stream.select("user_id", "event_id", "value").groupBy("user_id").transformWithStateInPandas(SkinTracker(), outputStructType="user_id long, rebuild int", outputMode="Append", timeMode="None")


@contextmanager
def rocks_state(spark: SparkSession):
    """State stores that hold several columns of state, as stateful processors need, for streams started inside."""
    name = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(name)
    spark.conf.set(name, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        yield
    finally:
        spark.conf.set(name, before)


def plain_frames(stream: DataFrame, width: str = "1 hour", late: str = "1 hour") -> DataFrame:
    framed = stream.withWatermark("at", late).groupBy(F.window("at", width).alias("w")).agg(F.count(F.lit(1)).alias("events"))
    return framed.select(F.unix_seconds("w.start").alias("frame_start"), "events")


def run_in_turn(spark: SparkSession, folders: list[str], make: Callable[[DataFrame], DataFrame], path: str) -> DataFrame:
    """Runs one stream over folders that arrive one after another, in append mode, and returns all that came out."""
    df = None
    for folder in folders:
        spark.read.parquet(folder).write.mode("append").parquet(f"{path}/in")
        df = make(spark.readStream.schema(_EVENTS).parquet(f"{path}/in").withColumn("at", F.col("ts").cast("timestamp")))
        run_available(df, path)
    return spark.read.schema(df.schema).parquet(f"{path}/out")


def run_available(df: DataFrame, path: str, mode: str = "append") -> DataFrame:
    """Runs a stream over all that is there now, into Parquet under path, and returns the table."""
    query = df.writeStream.outputMode(mode).option("checkpointLocation", f"{path}/_state").trigger(availableNow=True).format("parquet").start(f"{path}/out")
    query.awaitTermination()
    spark = df.sparkSession
    return spark.read.schema(df.schema).parquet(f"{path}/out")


def run_batches(df: DataFrame, path: str, mode: str = "update") -> DataFrame:
    """The same through foreachBatch, each batch in its own folder; later batches replace rows of earlier ones."""

    def each(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{path}/out/batch={number}")

    df.writeStream.outputMode(mode).option("checkpointLocation", f"{path}/_state").trigger(availableNow=True).foreachBatch(each).start().awaitTermination()
    return df.sparkSession.read.option("recursiveFileLookup", True).parquet(f"{path}/out")

"""Structured Streaming twins: FINAL as append mode with a watermark, the verbose form as update mode."""

from __future__ import annotations

from collections.abc import Callable
from datetime import timedelta

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def micros(d: timedelta) -> str:
    return f"{round(d.total_seconds() * 1e6)} microseconds"


def windowed_stream(rows: DataFrame, column: str, keys: list[str], aggregates: list[Column], size: timedelta, advance: timedelta | None, grace: timedelta, start: int = 0) -> DataFrame:
    """A windowed aggregate over a stream. Zone-less times are cast, for watermarks need an instant; ``start`` is the
    place of the first range in microseconds, and ranges before it are left out."""
    step = round((advance or size).total_seconds() * 1e6)
    at = F.col(column).cast("timestamp")
    w = F.window("_at", micros(size), f"{step} microseconds", f"{start % step} microseconds")
    made = rows.withColumn("_at", at).withWatermark("_at", micros(grace)).groupBy(*keys, w.alias("_w")).agg(*aggregates)
    made = made.filter(F.unix_micros("_w.start") >= start)
    return made.withColumn("win_start", F.col("_w.start").cast("timestamp_ntz")).withColumn("win_end", F.col("_w.end").cast("timestamp_ntz")).drop("_w")


class CommitFeed:
    """Gives the slices of commits to a stream one after another: each lands in the source folder and is run through
    (``availableNow``) before the next, so micro-batches are commits."""

    def __init__(self, spark: SparkSession, place: str, schema: T.StructType):
        self.spark, self.place, self.schema = spark, place.rstrip("/"), schema

    def stream(self) -> DataFrame:
        return self.spark.readStream.schema(self.schema).parquet(f"{self.place}/in")

    def push(self, rows: DataFrame) -> None:
        rows.select(*self.schema.fieldNames()).write.mode("append").parquet(f"{self.place}/in")

    def run(self, query: DataFrame, mode: str, sink: Callable[[DataFrame, int], None] | None = None) -> None:
        out = query.writeStream.outputMode(mode).option("checkpointLocation", f"{self.place}/state").trigger(availableNow=True)
        if sink:
            started = out.foreachBatch(sink).start()
        else:
            started = out.format("parquet").option("path", f"{self.place}/out").start()
        started.awaitTermination()


def final_stream(feed: CommitFeed, slices: list[DataFrame], build: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """All rows that append mode gives over the slices. An empty tail lets the last watermark close its ranges."""
    for rows in slices:
        feed.push(rows)
        feed.run(build(feed.stream()), "append")
    return feed.spark.read.parquet(f"{feed.place}/out")


def verbose_stream(feed: CommitFeed, slices: list[DataFrame], build: Callable[[DataFrame], DataFrame], name: str) -> DataFrame:
    """All corrections that update mode gives (images after alone), with the number of the batch."""

    def sink(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number).cast("long")).write.mode("append").parquet(f"{feed.place}/{name}")

    for rows in slices:
        feed.push(rows)
        feed.run(build(feed.stream()), "update", sink)
    return feed.spark.read.parquet(f"{feed.place}/{name}")

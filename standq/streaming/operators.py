"""Streaming operators around the engine's flows, and the stateful verbose form with images before and after."""

from __future__ import annotations

from collections.abc import Iterator
from datetime import timedelta
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.streaming.query import StreamingQuery

from standq.streaming.final_stream import micros

ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def rate_stream(spark: SparkSession, rows_per_second: int) -> DataFrame:
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()


def to_memory(rows: DataFrame, name: str, mode: str = "append") -> StreamingQuery:
    """A small result as a table of the session, for tests and looking."""
    return rows.writeStream.format("memory").queryName(name).outputMode(mode).start()


def dedup_within(rows: DataFrame, column: str, keys: list[str], grace: timedelta) -> DataFrame:
    """One row of each key while its copies come no later than ``grace`` after one another; state is let go behind it."""
    return rows.withColumn("_at", F.col(column).cast("timestamp")).withWatermark("_at", micros(grace)).dropDuplicatesWithinWatermark(keys).drop("_at")


def interval_join(left: DataFrame, right: DataFrame, on: str, at: str, other: str, within: timedelta, grace: timedelta) -> DataFrame:
    """Pairs of two streams with ``other`` in [at, at + within]; the bound lets both sides' state go. ``on``, ``at`` and
    ``other`` must be named apart but for ``on``; times come back as instants."""
    a = left.withColumn(at, F.col(at).cast("timestamp")).withWatermark(at, micros(grace)).alias("a")
    b = right.withColumn(other, F.col(other).cast("timestamp")).withWatermark(other, micros(grace)).alias("b")
    span = F.expr(f"interval {round(within.total_seconds() * 1000)} milliseconds")
    near = (F.col(f"b.{other}") >= F.col(f"a.{at}")) & (F.col(f"b.{other}") <= F.col(f"a.{at}") + span)
    return a.join(b, (F.col(f"a.{on}") == F.col(f"b.{on}")) & near).select("a.*", *(f"b.{c}" for c in right.columns if c != on))


def split_late(batch: DataFrame, column: str, frontier: Any) -> tuple[DataFrame, DataFrame]:
    """A micro-batch against a persisted frontier: rows in time, rows late."""
    if frontier is None:
        return batch, batch.limit(0)
    late = F.col(column) < F.lit(frontier)
    return batch.filter(~late), batch.filter(late)


class Corrections(StatefulProcessor):
    """Keeps the sum of a key; every batch that moves it gives the old value with sign -1 and the new one with 1.

    With a time to live the state of a key that nothing touches goes, as expired rows do.
    """

    def __init__(self, value: str, ttl: timedelta | None = None):
        self.value, self.ttl = value, ttl

    def init(self, handle: StatefulProcessorHandle) -> None:
        ms = None if self.ttl is None else round(self.ttl.total_seconds() * 1000)
        self.total = handle.getValueState("total", "total decimal(38,4)", ms)

    def handleInputRows(self, key: Any, rows: Iterator[pd.DataFrame], timers: Any) -> Iterator[pd.DataFrame]:
        add = sum((v for part in rows for v in part[self.value]), 0)
        old = self.total.get()[0] if self.total.exists() else None
        new = add if old is None else old + add
        self.total.update((new,))
        if old is None or new != old:
            signs = [(1, new)] if old is None else [(-1, old), (1, new)]
            yield pd.DataFrame({**{f"k{i}": [k] * len(signs) for i, k in enumerate(key)}, "sign": [s for s, _ in signs], "total": [float(t) for _, t in signs]})

    def close(self) -> None:
        pass


def verbose_corrections(rows: DataFrame, keys: list[str], value: str, ttl: timedelta | None = None) -> DataFrame:
    """The verbose form over a stream: k0, k1, .. (the keys), sign, total. Needs the RocksDB state store (``ROCKS`` in
    spark.sql.streaming.stateStore.providerClass); ``value`` is a decimal column."""
    kinds = ", ".join(f"k{i} {rows.schema[k].dataType.simpleString()}" for i, k in enumerate(keys))
    return rows.groupBy(*keys).transformWithStateInPandas(
        Corrections(value, ttl), f"{kinds}, sign int, total double", "Update", "ProcessingTime" if ttl else "None"
    )

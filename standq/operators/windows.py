"""The window table function, pane aggregation and sessions."""

from __future__ import annotations

import math
from datetime import timedelta
from typing import Any

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from standq.functions.ranges import Axis, range_end, range_ids, range_start


def window_table(
    rows: DataFrame, column: str, size: Any, advance: Any = None, start_with: Any = None, names: tuple[str, str] = ("win_start", "win_end"), bounds: str = "half_open"
) -> DataFrame:
    """Every row once for each range that holds it, with the range's bounds. Ranges that would begin before ``start_with``
    do not exist; with ``advance`` beyond ``size`` some rows are in none. ``bounds='inclusive'`` shows the last unit.

    Sizes are intervals (``timedelta``), ``Months`` for calendar lengths, or numbers for a numeric column. Rows with a null
    place are in no range.
    """
    advance = size if advance is None else advance
    axis = Axis(rows.schema[column].dataType, size)
    r, a, s = axis.length(size), axis.length(advance), axis.start(start_with)
    if r <= 0 or a <= 0:
        raise ValueError("range and advance must be positive")
    place = axis.of(F.col(f"`{column}`"))
    out = rows.withColumn("_i", F.explode(range_ids(place, r, a, s)))
    end = range_end(F.col("_i"), a, r, s)
    if bounds == "inclusive":
        end = end - (1 if axis.unit != "micros" else 1)
    return out.withColumn(names[0], axis.back(range_start(F.col("_i"), a, s))).withColumn(names[1], axis.back(end)).drop("_i")


def hop_aggregate(
    rows: DataFrame, column: str, keys: list[str], aggregates: dict[str, tuple[str, str]], size: timedelta, advance: timedelta | None = None, start_with: Any = None, strategy: str = "panes"
) -> DataFrame:
    """Aggregates for each key and range: name -> (sum | count | min | max | avg, expression).

    ``panes`` first aggregates in slices as long as the greatest common divisor of range and advance, so the shuffle
    carries one row a slice and key and not one a row and range; ``explode`` copies rows; ``native`` uses ``window``.
    """
    advance = advance or size
    if strategy == "explode":
        return window_table(rows, column, size, advance, start_with).groupBy(*keys, "win_start", "win_end").agg(*(final(n, f, F.expr(c)) for n, (f, c) in aggregates.items()))
    axis = Axis(rows.schema[column].dataType, size)
    r, a, s = axis.length(size), axis.length(advance), axis.start(start_with)
    if strategy == "native":
        shift = s % a
        at = F.window(F.col(column).cast("timestamp"), f"{r} microseconds", f"{a} microseconds", f"{shift} microseconds")
        made = rows.withColumn("_w", at).groupBy(*keys, "_w").agg(*(final(n, f, F.expr(c)) for n, (f, c) in aggregates.items()))
        kind = rows.schema[column].dataType
        made = made.withColumn("win_start", F.col("_w.start").cast(kind)).withColumn("win_end", F.col("_w.end").cast(kind)).drop("_w")
        return made.filter(F.unix_micros(F.col("win_start").cast("timestamp")) >= s).select(*keys, "win_start", "win_end", *aggregates)
    pane = math.gcd(r, a)
    parts = {f"_{n}_{k}": e for n, (f, c) in aggregates.items() for k, e in partial(f, F.expr(c)).items()}
    slices = rows.withColumn("_p", F.floor((axis.of(F.col(column)) - s) / pane)).filter("_p >= 0").groupBy(*keys, "_p").agg(*(e.alias(n) for n, e in parts.items()))
    hopped = slices.withColumn("_i", F.explode(range_ids(F.col("_p") * pane + s, r, a, s)))
    merged = hopped.groupBy(*keys, "_i").agg(*(merge(n, f) for n, (f, _) in aggregates.items()))
    return merged.select(
        *keys, axis.back(range_start(F.col("_i"), a, s)).alias("win_start"), axis.back(range_end(F.col("_i"), a, r, s)).alias("win_end"), *aggregates
    )


def final(name: str, f: str, c: Column) -> Column:
    return {"sum": F.sum, "count": F.count, "min": F.min, "max": F.max, "avg": F.avg}[f](c).alias(name)


def partial(f: str, c: Column) -> dict[str, Column]:
    return {"sum": {"s": F.sum(c)}, "count": {"n": F.count(c)}, "min": {"m": F.min(c)}, "max": {"m": F.max(c)}, "avg": {"s": F.sum(c), "n": F.count(c)}}[f]


def merge(name: str, f: str) -> Column:
    part = lambda k: F.col(f"_{name}_{k}")
    return {"sum": lambda: F.sum(part("s")), "count": lambda: F.sum(part("n")), "min": lambda: F.min(part("m")), "max": lambda: F.max(part("m")), "avg": lambda: F.sum(part("s")) / F.sum(part("n"))}[f]().alias(name)


def session_table(rows: DataFrame, column: str, gap: str, by: list[str], aggregates: list[Column]) -> DataFrame:
    """Sessions that end after ``gap`` without a row, for each key."""
    kind = rows.schema[column].dataType
    at = F.session_window(F.col(column).cast("timestamp"), gap)
    made = rows.withColumn("_s", at).groupBy(*by, "_s").agg(*aggregates)
    return made.withColumn("win_start", F.col("_s.start").cast(kind)).withColumn("win_end", F.col("_s.end").cast(kind)).drop("_s")

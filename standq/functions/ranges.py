"""Time and number ranges: which ranges hold a value, and where a range starts and ends."""

from __future__ import annotations

from datetime import date, datetime, timedelta
from typing import Any

from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T

DAY = 86_400_000_000


class Months(int):
    """A number of calendar months, for ranges of calendar length."""


class Axis:
    """Places on a column as whole or floating numbers, and back: microseconds, days, months or the number itself."""

    def __init__(self, kind: T.DataType, span: Any):
        self.kind = kind
        self.months = isinstance(span, Months)
        name = kind.typeName()
        self.unit = "months" if self.months else "days" if name == "date" else "micros" if name in ("timestamp", "timestamp_ntz") else "number"
        if self.unit == "number" and not isinstance(kind, T.NumericType):
            raise ValueError(f"no ranges over {name}")

    def of(self, c: Column) -> Column:
        if self.unit == "months":
            return F.year(c) * 12 + F.month(c) - 1
        if self.unit == "days":
            return F.datediff(c, F.lit("1970-01-01").cast("date")).cast("long")
        return F.unix_micros(c.cast("timestamp")) if self.unit == "micros" else c

    def back(self, place: Column) -> Column:
        if self.unit == "months":
            first = F.add_months(F.lit("0000-01-01").cast("date"), place.cast("int"))
            return first.cast(self.kind)
        if self.unit == "days":
            return F.date_add(F.lit("1970-01-01").cast("date"), place.cast("int"))
        return F.timestamp_micros(place.cast("long")).cast(self.kind) if self.unit == "micros" else place.cast(self.kind)

    def length(self, v: Any) -> int | float:
        if isinstance(v, timedelta):
            return round(v.total_seconds() * 1e6) // (DAY if self.unit == "days" else 1)
        return int(v) if self.months else v

    def start(self, v: Any) -> int | float:
        if self.unit == "number":
            return 0 if v is None else v
        if v is None:
            v = date(1970, 1, 1) if self.unit == "days" else datetime(1970, 1, 1)
        if self.unit == "months":
            return v.year * 12 + v.month - 1
        if self.unit == "days":
            return (v - date(1970, 1, 1)).days
        return round((v - datetime(1970, 1, 1)).total_seconds() * 1e6)


def range_ids(place: Column, size: Any, advance: Any, start: Any) -> Column:
    """Numbers i >= 0 of the ranges [start + i advance, start + i advance + size) that hold a place, rising."""
    low = F.greatest(F.lit(0), (F.floor((place - start - size) / F.lit(advance)) + 1).cast("long"))
    high = F.floor((place - start) / F.lit(advance)).cast("long")
    none = F.array().cast("array<bigint>")
    return F.when(low <= high, F.sequence(low, high)).otherwise(none)


def range_start(i: Column, advance: Any, start: Any) -> Column:
    return i * F.lit(advance) + F.lit(start)


def range_end(i: Column, advance: Any, size: Any, start: Any) -> Column:
    return range_start(i, advance, start) + F.lit(size)


def register_range_function(spark: Any, name: str = "range_numbers") -> None:
    """``SELECT * FROM range_numbers(place, size, advance, start)``: the same numbers as a table function for SQL text."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="i bigint")
    class Numbers:
        def eval(self, place: float, size: float, advance: float, start: float):
            if place is None:
                return
            low = max(0, int((place - start - size) // advance) + 1)
            for i in range(low, int((place - start) // advance) + 1):
                yield (i,)

    spark.udtf.register(name, Numbers)

"""Increasing columns, grace, and what becomes of late rows."""

from __future__ import annotations

from dataclasses import dataclass
from datetime import date, datetime, timedelta
from typing import Any

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from standq.errors import ConstraintViolation


@dataclass
class Increasing:
    """New values are not below the maximum less ``grace``; with ``strict`` they are above it.

    ``timing`` is immediate (at each statement) or deferred (at commit). ``rely`` takes the property as given. With ``by``
    the maximum is that of the row's own key, looked up in the table by a join on the keys of the statement.
    """

    column: str
    strict: bool = False
    grace: Any = None
    timing: str = "immediate"
    rely: bool = False
    nulls_ok: bool = False
    by: tuple[str, ...] = ()

    def state(self) -> dict[str, Any]:
        return {"strict": self.strict, "grace": self.pack(self.grace), "timing": self.timing, "enabled": not self.rely, "max": None, "nulls_ok": self.nulls_ok, "by": list(self.by)}

    @staticmethod
    def pack(v: Any) -> Any:
        """A value as JSON that says its type."""
        for kind in (datetime, date):
            if isinstance(v, kind):
                return {"t": kind.__name__, "v": v.isoformat()}
        return {"t": "timedelta", "v": v.total_seconds()} if isinstance(v, timedelta) else v

    @staticmethod
    def unpack(v: Any) -> Any:
        if not isinstance(v, dict):
            return v
        return {"datetime": datetime.fromisoformat, "date": date.fromisoformat, "timedelta": lambda s: timedelta(seconds=s)}[v["t"]](v["v"])

    @classmethod
    def max_of(cls, state: dict[str, Any]) -> Any:
        return cls.unpack(state["max"])

    @classmethod
    def grace_of(cls, state: dict[str, Any]) -> Any:
        return cls.unpack(state["grace"])

    @classmethod
    def advance(cls, state: dict[str, Any], top: Any) -> None:
        if top is not None and (state["max"] is None or top > cls.max_of(state)):
            state["max"] = cls.pack(top)

    @classmethod
    def frontier(cls, state: dict[str, Any], grace: Any = None) -> Any:
        """Maximum less grace: nothing below it is accepted any longer."""
        top, g = cls.max_of(state), grace if grace is not None else cls.grace_of(state)
        return None if top is None else top - g if g is not None else top

    def to_predicate(self, top: str) -> str:
        """The same property as a finalization predicate over the column, given an expression of the maximum."""
        if self.grace is not None:
            g = f"INTERVAL '{self.grace.total_seconds():.0f}' SECOND" if isinstance(self.grace, timedelta) else str(self.grace)
            return f"{self.column} {'<=' if self.strict else '<'} {top} - {g}"
        return f"{self.column} {'<=' if self.strict else '<'} {top}"


def check_increasing_by(state: dict[str, Any], new: DataFrame, held: DataFrame, column: str) -> None:
    """The property for every key by itself; only keys of the statement are looked up."""
    by, grace = state["by"], Increasing.grace_of(state)
    tops = held.join(new.select(*by).distinct(), by, "left_semi").groupBy(*by).agg(F.max(column).alias("_top"))
    bad = new.join(tops, by).filter(_below(F.col(column), F.col("_top"), grace, state["strict"])).limit(1).collect()
    if bad:
        raise ConstraintViolation(f"{column}: {bad[0][column]} is behind {bad[0]['_top']} of its key")


def as_watermark(rows: DataFrame, column: str, state: dict[str, Any]) -> DataFrame:
    """The constraint's grace as a stream's watermark (an instant is needed, so zone-less times are cast)."""
    grace = Increasing.grace_of(state)
    seconds = 0 if grace is None else grace.total_seconds()
    return rows.withColumn(column, F.col(column).cast("timestamp")).withWatermark(column, f"{round(seconds * 1e6)} microseconds")


def check_increasing(state: dict[str, Any], least: Any, column: str) -> None:
    bound = Increasing.frontier(state)
    if bound is None or least is None or not state["enabled"]:
        return
    if least < bound or (state["strict"] and least == bound):
        raise ConstraintViolation(f"{column}: {least} is {'not above' if state['strict'] else 'below'} {bound}")


@dataclass
class Late:
    """Rows of an insert that are below the frontier: ``error``, ``ignore``, or into the table ``side``."""

    mode: str = "error"
    side: str | None = None

    def split(self, tx: Any, table: Any, rows: DataFrame) -> DataFrame:
        if self.mode == "error":
            return rows
        late: Column = F.lit(False)
        for c, state in table.meta.increasing.items():
            bound = Increasing.frontier(state)
            if bound is not None:
                late = late | (F.col(f"`{c}`") <= F.lit(bound) if state["strict"] else F.col(f"`{c}`") < F.lit(bound))
        if self.mode == "side" and self.side:
            tx.insert(self.side, rows.filter(late))
        return rows.filter(~late)


def mark_late(rows: DataFrame, column: str, order: list[str], grace: Any = None, strict: bool = False, by: list[str] | None = None, of_a_range: int = 500_000) -> DataFrame:
    """One row a statement, in ``order``: adds ``_late`` against the running maximum of what came before (of ``by``).

    Without ``by`` the running maximum is taken in two levels, so that no task sees all rows: maxima of ranges of the
    first order column (about ``of_a_range`` rows each), then a running maximum in each range that starts from the maxima
    of the ranges before.
    """
    from pyspark.sql import Window

    c = F.col(column)
    keys = [F.col(o) for o in order]
    if by:
        w = Window.partitionBy(*by).orderBy(*keys).rowsBetween(Window.unboundedPreceding, -1)
        return rows.withColumn("_top", F.max(c).over(w)).withColumn("_late", _below(c, F.col("_top"), grace, strict)).drop("_top")
    first = F.col(order[0])
    place = F.unix_micros(first.cast("timestamp")).cast("double") if dict(rows.dtypes)[order[0]] in ("timestamp_ntz", "timestamp", "date") else first.cast("double")
    low, high, n = rows.agg(F.min(place), F.max(place), F.count("*")).first()
    ranges = min(1_000_000, max(16, n // of_a_range))
    width = max((high - low) / ranges, 1e-9) if low is not None else 1.0
    dealt = rows.withColumn("_range", F.floor((place - F.lit(low if low is not None else 0.0)) / width).cast("int"))
    tops = dealt.groupBy("_range").agg(F.max(c).alias("_most"))  # one row a range, a million at most
    starts = tops.select("_range", F.max("_most").over(Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)).alias("_start"))
    own = Window.partitionBy("_range").orderBy(*keys).rowsBetween(Window.unboundedPreceding, -1)
    out = dealt.join(F.broadcast(starts), "_range").withColumn("_top", F.greatest(F.max(c).over(own), F.col("_start")))
    return out.withColumn("_late", _below(c, F.col("_top"), grace, strict)).drop("_top", "_start", "_range")


def _below(c: Column, top: Column, grace: Any, strict: bool) -> Column:
    bound = top if grace is None else top - F.lit(grace)
    return F.coalesce(c <= bound if strict else c < bound, F.lit(False))

"""Results that are given only once they can no longer change: closed ranges, finalization predicates, watermarks."""

from __future__ import annotations

import math
import re
from dataclasses import dataclass
from datetime import datetime, timedelta
from fractions import Fraction
from typing import Any

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from standq.errors import ConstraintViolation, NotInsertOnly, UnboundedState
from standq.functions.ranges import Axis
from standq.operators.constraints import Increasing
from standq.operators.windows import final as one
from standq.operators.windows import hop_aggregate, window_table
from standq.plans.relation import Aggregate, Filter, Relation, Scan, WindowTable, key_id
from standq.sources.store import TIMES, Table, parse_value

#: Distinct values that are counted one by one to find a percentile.
EXACT = 100_000


def frontiers(table: Table, column: str, version: int, grace: Any = None) -> list[tuple[int, Any]]:
    """(commit, maximum of the column in the commits up to it, less grace), for the commits that raised it: from the
    manifests; where they do not hold the column's extremes, from one aggregate over that column."""
    kind, since = table.schema[column].dataType.simpleString(), table.meta.since
    own = [(m["commit"], m["tables"][table.name]) for m in table.db.manifests[since:version] if table.name in m["tables"]]
    if all(column in e["stats"] or not e["files"] for _, e in own):
        tops = [(n, e["stats"][column][1]) for n, e in own if column in e["stats"]]
        tops = [(n, parse_value(t, kind)) for n, t in tops if t not in (None, "None")]
    else:
        log = table.log_slice(0, version).filter("_action <> 'DELETE'")
        per = log.groupBy("_commit_no").agg(F.max(F.col(f"`{column}`")).alias("top")).filter("top is not null").orderBy("_commit_no")
        tops = [(r._commit_no, r.top) for r in per.collect()]  # one row a commit
    out: list[tuple[int, Any]] = []
    for n, top in tops:
        top = top - grace if grace is not None else top
        if not out or top > out[-1][1]:
            out.append((n, top))
    return out


def frontier(table: Table, column: str, version: int, grace: Any = None) -> Any:
    """Maximum of the column in the commits up to ``version``, less grace."""
    found = frontiers(table, column, version, grace)
    return found[-1][1] if found else None


def resolve_grace(table: Table, column: str, clause: Any = None) -> Any:
    """The clause counts, else the column's constraint, else there is none."""
    if clause is not None:
        return clause
    state = table.meta.increasing.get(column)
    return Increasing.grace_of(state) if state else None


def require_bounded(table: Table, column: str, clause: Any = None) -> None:
    if column not in table.meta.increasing and clause is None:
        raise UnboundedState(f"{column} is not increasing and no grace is given: ranges would stay open for ever")


def state_bound(size: Any, advance: Any, grace: Any = None) -> int:
    """Most ranges of one key that are open at a time."""
    span = size + grace if grace is not None else size
    ratio = span / advance
    return int(ratio) + (ratio > int(ratio)) + 1


class FinalWindow(Relation):
    """FINAL of a windowed aggregate over an insert-only table: each range once, when it is closed.

    ``tight``: closed as soon as no accepted row can fall in, max - grace >= end. ``literal``: max > end + grace.
    A closed range stays as it was: rows that come for it later (where the clause's grace is less than what the column
    admits, or the column has no constraint) do not count in it. Only rows of the ranges that close are read.
    """

    def __init__(self, child: Scan, column: str, keys: list[str], aggregates: dict[str, tuple[str, str]], size: Any, advance: Any = None, start_with: Any = None, grace: Any = None, closure: str = "tight", strategy: str = "panes"):
        if not child.table.meta.insert_only:
            raise NotInsertOnly(f"{child.table.name} is not insert-only")
        require_bounded(child.table, column, grace)
        self.inputs, self.db, self.table, self.column, self.keys, self.aggregates = (child,), child.db, child.table, column, keys, aggregates
        self.size, self.advance, self.start_with, self.closure, self.way = size, advance or size, start_with, closure, strategy
        self.grace = resolve_grace(child.table, column, grace)

    def _late(self) -> bool:
        """Whether a row may come for a range that is closed: the clause's grace is less than what the column admits."""
        state = self.table.meta.increasing.get(self.column)
        if state is None or not state["enabled"] or state.get("by"):
            return True
        own = Increasing.grace_of(state)
        return own is not None and (self.grace is None or own > self.grace)

    def _closed(self, version: int, upto: Any, after: Any = None) -> DataFrame:
        c = F.col(f"`{self.column}`")
        rows = self.table.log_slice(0, version).filter(c < F.lit(upto))
        if after is not None:
            rows = rows.filter(c >= F.lit(after - self.size))
        end = F.col("win_end")
        if self._late():
            # a row counts in a range only if the range was open at the row's commit
            known = frontiers(self.table, self.column, version, self.grace)
            rows = self._with_frontier(rows, known)
            rows = window_table(rows, self.column, self.size, self.advance, self.start_with)
            was_open = F.col("_then").isNull() | (end > F.col("_then") if self.closure == "tight" else end >= F.col("_then"))
            calls = [one(n, f, F.expr(e)) for n, (f, e) in self.aggregates.items()]
            made = rows.filter(was_open).groupBy(*(F.col(f"`{k}`") for k in self.keys), "win_start", "win_end").agg(*calls)
        else:
            rows = rows.select(*(F.col(f"`{n}`") for n in self.table.columns))
            made = hop_aggregate(rows, self.column, self.keys, self.aggregates, self.size, self.advance, self.start_with, self.way)
        made = made.filter(end <= F.lit(upto) if self.closure == "tight" else end < F.lit(upto))
        if after is not None:
            made = made.filter(end > F.lit(after) if self.closure == "tight" else end >= F.lit(after))
        return made.withColumn("_row_id", key_id([*self.keys, "win_start"]))

    def _with_frontier(self, rows: DataFrame, known: list[tuple[int, Any]]) -> DataFrame:
        """``_then``: the frontier before the row's commit; from one row a commit that raised it."""
        spark, kind = self.db.spark, rows.schema[self.column].dataType.simpleString()
        spans = [(n + 1, known[i + 1][0] if i + 1 < len(known) else 1 << 62, top) for i, (n, top) in enumerate(known)]
        table = spark.createDataFrame(spans, f"_from long, _to long, _then {kind}")
        return rows.join(F.broadcast(table), F.col("_commit_no").between(F.col("_from"), F.col("_to")), "left")

    def at(self, version):
        top = frontier(self.table, self.column, version, self.grace)
        if top is None:
            return self._closed(version, datetime(1970, 1, 1) if self.table.schema[self.column].dataType.simpleString() in TIMES else 0).limit(0)
        return self._closed(version, top)

    def delta(self, v0, v1):
        before, now = (frontier(self.table, self.column, v, self.grace) for v in (v0, v1))
        if now is None or now == before:
            return self.at(0).withColumn("_sign", F.lit(1))
        return self._closed(v1, now, before).withColumn("_sign", F.lit(1))

    def strategy(self):
        return "closing ranges"

    def insert_only(self, rules="paper"):
        return True, "X1 final"


# Monotone predicates


def bucket_upper_bound(expr: str, column: str) -> str | None:
    """An expression that no value of the bucket reaches, for buckets of a column known to be monotone; None if not known."""
    e = expr.strip()
    if e in (column, f"`{column}`"):
        return None if not e else f"{e}"
    if m := re.fullmatch(rf"date_trunc\(\s*'(\w+)'\s*,\s*{re.escape(column)}\s*\)", e, re.I):
        return f"{e} + INTERVAL '1' {m[1].upper()}"
    if re.fullmatch(rf"(?:date|to_date)\(\s*{re.escape(column)}\s*\)|cast\(\s*{re.escape(column)}\s+as\s+date\s*\)", e, re.I):
        return f"date_add({e}, 1)"
    if re.fullmatch(rf"floor\(\s*{re.escape(column)}\s*\)", e, re.I):
        return f"{e} + 1"
    return None


@dataclass
class Watermark:
    """A bound below which no row will come any more, persisted so that it never falls."""

    value: Any

    @classmethod
    def from_table(cls, table: Table, column: str, version: int | None = None) -> Watermark:
        """Greatest value of another stream's column; from manifests where it is constrained, else one aggregate."""
        version = table.db.version if version is None else version
        top = frontier(table, column, version) if column in table.meta.increasing else None
        return cls(top if top is not None else table.snapshot(version).agg(F.max(column)).first()[0])

    @classmethod
    def percentile(cls, rows: DataFrame, column: str, p: float, before: Watermark | None = None, accuracy: int = 10_000) -> Watermark:
        """A percentile of the values so far; a late low value cannot pull it below what it was.

        It is the value of that rank, exactly. Estimates (of ``accuracy``) bound it; the rows between the bounds are bounded
        again until their distinct values are at most ``EXACT``, and these are counted.
        """
        kind = rows.schema[column].dataType
        axis = Axis(kind, timedelta(1) if kind.typeName() != "double" else 1)
        x = rows.select(axis.of(F.col(column)).alias("x")).filter("x IS NOT NULL")
        found = cls._ranked(x, Fraction(str(p)), accuracy)
        value = None if found is None else rows.sparkSession.range(1).select(axis.back(F.lit(found).cast(x.schema["x"].dataType)).alias("v")).first()[0]
        return cls(value if before is None or before.value is None or (value is not None and value > before.value) else before.value)

    @staticmethod
    def _ranked(x: DataFrame, p: Fraction, accuracy: int):
        """The value of rank p * n, rounded up, of the n values of ``x``."""
        n = x.count()
        rank, lo, hi = max(1, math.ceil(p * n)), None, None
        while n:
            off = 2 / accuracy + 1 / n  # further than estimates are wrong
            low, high = max(0.0, rank / n - off), min(1.0, rank / n + off)
            a, b, top = x.agg(F.percentile_approx("x", [low, high], accuracy).alias("q"), F.max("x").alias("m")).select(F.col("q")[0], F.col("q")[1], "m").first()
            b = top if high == 1.0 else b
            below, upto = x.agg(F.count_if(F.col("x") < F.lit(a)), F.count_if(F.col("x") <= F.lit(b))).first()
            if below < rank <= upto and (a, b) != (lo, hi):
                x, rank, n, lo, hi = x.filter(F.col("x").between(F.lit(a), F.lit(b))), rank - below, upto - below, a, b
                if a == b:
                    return a
            else:  # no nearer by estimates
                break
            if x.select("x").distinct().limit(EXACT + 1).count() <= EXACT:
                break
        if not n:
            return None
        for value, count in ((r.x, r.n) for r in x.groupBy("x").agg(F.count("*").alias("n")).orderBy("x").toLocalIterator()):
            rank -= count
            if rank <= 0:
                return value

    @classmethod
    def by(cls, rows: DataFrame, column: str, sources: list[str]) -> Watermark:
        """The least of the sources' maxima: every source has passed it."""
        return cls(rows.groupBy(*sources).agg(F.max(column).alias("m")).agg(F.min("m")).first()[0])

    def final_rows(self, rows: DataFrame, column: str, inclusive: bool = False) -> DataFrame:
        """FINAL of a plain query: the rows that the bound has passed; the filter reaches the scan."""
        if self.value is None:
            return rows.limit(0)
        c = F.col(column)
        return rows.filter(c <= F.lit(self.value) if inclusive else c < F.lit(self.value))

    def final_groups(self, rows: DataFrame, column: str, bucket: str, keys: list[str], aggregates: list[Column]) -> DataFrame:
        """FINAL of a grouping by a monotone bucket: groups that no later row can enter."""
        bound = bucket_upper_bound(bucket, column)
        if bound is None:
            raise ConstraintViolation(f"no bound is known for groups by {bucket}")
        if self.value is None:
            return rows.limit(0).groupBy(*keys, F.expr(bucket).alias("bucket")).agg(*aggregates)
        within = rows.filter(F.col(column) < F.lit(self.value)).filter(F.expr(bound).cast(rows.schema[column].dataType) <= F.lit(self.value))
        return within.groupBy(*keys, F.expr(bucket).alias("bucket")).agg(*aggregates)


class Finalize(Filter):
    """A finalization predicate attached to a query; the source is not touched. FINAL of it gives the rows it holds for."""

    def strategy(self):
        return "linear"


def final(rel: Relation, on_expired: str = "error", now: Any = None) -> DataFrame:
    """FINAL of a relation: closed ranges, final rows, or all rows if none of them may expire unseen."""
    from standq.operators.expire import final_live

    if isinstance(rel, FinalWindow | Finalize):
        return rel.to_df()
    if isinstance(rel, Scan):
        if rel.table.meta.finalize:
            return rel.to_df().filter(F.expr(rel.table.meta.finalize))
        return final_live(rel.table, "true", now) if rel.table.meta.expire else rel.to_df()
    if isinstance(rel, Aggregate):
        return final_of_aggregate(rel).to_df().select(*rel.keys, *rel.aggregates)
    raise UnboundedState(f"no finality is known for {type(rel).__name__}")


CALL = re.compile(r"\s*(sum|count|min|max|avg)\s*\((.*)\)\s*", re.I | re.S)


def final_of_aggregate(rel: Aggregate) -> FinalWindow:
    """FINAL of a grouping by the bounds of a window table: both bounds must be among the keys, for no grouping is hidden."""
    child = rel.inputs[0]
    if not isinstance(child, WindowTable) or not isinstance(child.inputs[0], Scan):
        raise UnboundedState("groups of unknown bounds are never final; use a window or a bucket")
    if not {"win_start", "win_end"} <= set(rel.keys):
        raise UnboundedState("the bounds of the window must be grouping keys")
    calls = {n: CALL.fullmatch(e) for n, e in rel.aggregates.items()}
    if bad := [n for n, m in calls.items() if not m]:
        raise UnboundedState(f"not a plain aggregate: {bad}")
    aggregates = {n: (m[1].lower(), "1" if m[2].strip() == "*" else m[2]) for n, m in calls.items()}
    keys = [k for k in rel.keys if k not in ("win_start", "win_end")]
    return FinalWindow(child.inputs[0], child.column, keys, aggregates, child.size, child.advance, child.start_with, child.grace)


# The same meaning from plain SQL operators: baselines


def rewrite_windows(rows: DataFrame, column: str, keys: list[str], aggregates: list[Column], size: timedelta, advance: timedelta | None = None, start_with: Any = None, grace: timedelta | None = None, history: DataFrame | None = None) -> DataFrame:
    """Ranges for which some row is late enough (a semi join) and which were not given before (an anti join).

    One row decides for a range that it is over: its time is not before the range's end plus grace. The semi join takes
    the latest row alone, for any later row serves.
    """
    made = window_table(rows, column, size, advance or size, start_with).groupBy(*keys, "win_start", "win_end").agg(*aggregates)
    later = rows.agg(F.max(column).alias("_top"))
    bound = F.col("win_end") if grace is None else F.col("win_end") + F.lit(grace)
    out = made.join(later, F.col("_top") >= bound, "left_semi")
    if history is not None:
        on = [*keys, "win_start", "win_end"]
        out = out.join(history.select(*on), on, "left_anti")
    return out


def rewrite_windows_literal(rows: DataFrame, column: str, keys: list[str], aggregates: list[Column], size: timedelta, advance: timedelta | None = None, start_with: Any = None, grace: timedelta | None = None) -> DataFrame:
    """As above, with the rows themselves on the right side of the semi join."""
    made = window_table(rows, column, size, advance or size, start_with).groupBy(*keys, "win_start", "win_end").agg(*aggregates)
    bound = F.col("win_end") if grace is None else F.col("win_end") + F.lit(grace)
    return made.join(rows.select(F.col(column).alias("_later")), F.col("_later") >= bound, "left_semi")


def check_invariants(table: Table, column: str, fetches: list[DataFrame]) -> dict[str, int]:
    """Rows accepted below the frontier of their commit, and ranges given more than once; both must be zero."""
    log = table.log_slice().groupBy("_commit_no").agg(F.min(column).alias("lo"), F.max(column).alias("hi"))
    before = F.max("hi").over(Window.orderBy("_commit_no").rowsBetween(Window.unboundedPreceding, -1))  # one row a commit
    grace = resolve_grace(table, column)
    bound = F.col("before") if grace is None else F.col("before") - F.lit(grace)
    below = log.withColumn("before", before).filter(F.col("lo") < bound).count()
    twice = 0
    if fetches:
        every = fetches[0]
        for f in fetches[1:]:
            every = every.unionByName(f)
        keys = [c for c in every.columns if c in ("win_start", "win_end") or dict(every.dtypes)[c] == "string"]
        twice = every.groupBy(*keys).count().filter("count > 1").count()
    return {"below_frontier": below, "given_twice": twice}

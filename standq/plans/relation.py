"""Relations: a table or a query that can be read at any version, and whose changes between versions can be derived.

Every node knows its rows at a version (``at``), with an identity of each row, and its signed change between versions
(``delta``), derived from the changes of its inputs where a rule exists. Linear operators map changes; inner joins use
the change of one side against the other; all other operators recompute what the changed keys touch; what has no rule
compares two versions. ``strategy()`` says which of these a node uses.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field
from functools import cached_property
from typing import Any

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from standq.functions.compaction import compact_net, compact_update, consolidate, encode, from_signed, signed, value_columns
from standq.operators.windows import window_table
from standq.sources.store import Database, Table


def same(a: list[str], left: str, right: str) -> Column:
    out: Column = F.lit(True)
    for c in a:
        out = out & F.col(f"{left}.`{c}`").eqNullSafe(F.col(f"{right}.`{c}`"))
    return out


def touching(rows: DataFrame, keys: DataFrame, on: list[str]) -> DataFrame:
    """Rows whose key occurs in ``keys``; nulls match nulls."""
    return rows.alias("l").join(keys.select(*on).distinct().alias("k"), same(on, "l", "k"), "left_semi")


def applied(rows: DataFrame, change: DataFrame) -> DataFrame:
    """Rows with a consolidated change: those it takes away are told by their identity."""
    gone = change.filter("_sign < 0").select("_row_id")
    return rows.join(gone, "_row_id", "left_anti").select(*rows.columns).unionByName(change.filter("_sign > 0").select(*rows.columns))


def key_id(columns: list[str], tag: str = "g") -> Column:
    """Identity from values: each with its length, so that no two rows run together, and safe for nulls."""
    text = [F.col(f"`{c}`").cast("string") for c in columns]
    parts = [F.coalesce(F.concat(F.length(t).cast("string"), F.lit(":"), t), F.lit("n")) for t in text]
    return F.concat(F.lit(tag), F.sha2(F.concat_ws(",", *parts) if parts else F.lit(""), 256))


class Relation:
    """Base: comparison of two versions, which is right for every operator."""

    db: Database
    inputs: tuple[Relation, ...] = ()

    @cached_property
    def columns(self) -> list[str]:
        return [c for c in self.at(0).columns if c != "_row_id"]

    def at(self, version: int) -> DataFrame:
        raise NotImplementedError

    def delta(self, v0: int, v1: int) -> DataFrame:
        return self.difference(v0, v1)

    def difference(self, v0: int, v1: int) -> DataFrame:
        """Evaluate twice and cancel what is the same: the baseline."""
        return consolidate(self.at(v0).withColumn("_sign", F.lit(-1)).unionByName(self.at(v1).withColumn("_sign", F.lit(1))))

    def strategy(self) -> str:
        return "difference"

    def tables(self) -> set[str]:
        return set().union(*(i.tables() for i in self.inputs)) if self.inputs else set()

    def insert_only(self, rules: str = "paper") -> tuple[bool, str]:
        """Whether rows are only ever added, by the node rules; the prover does the same for SQL text."""
        return False, f"{type(self).__name__} is not among the rules"

    def _all_insert_only(self, rules: str) -> tuple[bool, str]:
        for i in self.inputs:
            ok, why = i.insert_only(rules)
            if not ok:
                return ok, why
        return True, type(self).__name__

    def explain(self, depth: int = 0) -> str:
        return "\n".join(["  " * depth + f"{type(self).__name__}: {self.strategy()}", *(i.explain(depth + 1) for i in self.inputs)])

    # rows now
    def to_df(self, version: int | None = None) -> DataFrame:
        return self.at(self.db.version if version is None else version).drop("_row_id")

    # building
    def where(self, condition: str) -> Filter:
        return Filter(self, condition)

    def select(self, **columns: str) -> Project:
        return Project(self, columns)

    def union_all(self, other: Relation) -> UnionAll:
        return UnionAll(self, other)

    def join(self, other: Relation, on: list[str], how: str = "inner") -> Relation:
        return Join(self, other, on) if how == "inner" else KeyedJoin(self, other, on, how)

    def aggregate(self, keys: list[str], **aggregates: str) -> Aggregate:
        return Aggregate(self, keys, aggregates)

    def distinct(self) -> Aggregate:
        return Aggregate(self, self.columns, {})

    def top(self, n: int, order: list[tuple[str, bool]]) -> TopK:
        return TopK(self, n, order)

    def rank(self, by: list[str], order: str, name: str = "rank", function: str = "rank()") -> Ranked:
        return Ranked(self, by, order, name, function)

    def window(self, column: str, size: Any, advance: Any = None, start_with: Any = None, grace: Any = None) -> WindowTable:
        return WindowTable(self, column, size, advance, start_with, grace)

    def changes(self, start: int = 0, format: str = "DELTA") -> Changes:  # noqa: A002
        return Changes(self, start, format)


@dataclass
class Scan(Relation):
    table: Table

    def __post_init__(self):
        self.db = self.table.db

    def at(self, version):
        return self.table.snapshot(version, with_id=True)

    def delta(self, v0, v1):
        if self.table.only_inserts(v1, v0):  # by what the commits did; the declaration may be younger than they are
            return self.table.log_slice(v0, v1).select(*self.table.columns, "_row_id", F.lit(1).alias("_sign"))
        return signed(compact_net(self.table.log_slice(v0, v1))).select(*self.table.columns, "_row_id", "_sign")

    def strategy(self):
        return "log slice"

    def tables(self):
        return {self.table.name}

    def insert_only(self, rules="paper"):
        return self.table.meta.insert_only, f"table {self.table.name}"


class Linear(Relation):
    """One input; a change passes through as the rows do."""

    def map(self, rows: DataFrame) -> DataFrame:
        raise NotImplementedError

    def at(self, version):
        return self.map(self.inputs[0].at(version))

    def delta(self, v0, v1):
        return self.map(self.inputs[0].delta(v0, v1))

    def strategy(self):
        return "linear"

    def insert_only(self, rules="paper"):
        return self._all_insert_only(rules)


class Filter(Linear):
    def __init__(self, child: Relation, condition: str):
        self.inputs, self.db, self.condition = (child,), child.db, condition

    def map(self, rows):
        return rows.filter(F.expr(self.condition))

    def insert_only(self, rules="paper"):
        from standq.plans.prover import monotone_text

        return self._all_insert_only(rules) if monotone_text(self.condition) else (False, f"condition may turn false: {self.condition}")


class Project(Linear):
    def __init__(self, child: Relation, columns: dict[str, str]):
        self.inputs, self.db, self.exprs = (child,), child.db, columns

    def map(self, rows):
        carried = [c for c in rows.columns if c.startswith("_")]
        return rows.select(*(F.expr(e).alias(n) for n, e in self.exprs.items()), *carried)

    def insert_only(self, rules="paper"):
        from standq.plans.prover import fixed, parse_expression

        bad = [e for e in self.exprs.values() if not fixed(parse_expression(e))]
        return (False, f"select list changes with time: {bad}") if bad else self._all_insert_only(rules)


class WindowTable(Linear):
    """All columns, win_start and win_end; the row's identity is carried with its range."""

    def __init__(self, child: Relation, column: str, size: Any, advance: Any = None, start_with: Any = None, grace: Any = None):
        self.inputs, self.db = (child,), child.db
        self.column, self.size, self.advance, self.start_with, self.grace = column, size, advance or size, start_with, grace

    def map(self, rows):
        out = window_table(rows, self.column, self.size, self.advance, self.start_with)
        return out.withColumn("_row_id", F.concat_ws("@", "_row_id", F.col("win_start").cast("string")))

    def insert_only(self, rules="paper"):
        return self._all_insert_only(rules)


class UnionAll(Relation):
    def __init__(self, left: Relation, right: Relation):
        self.inputs, self.db = (left, right), left.db

    def _both(self, f):
        tagged = [f(i).withColumn("_row_id", F.concat(F.lit(f"{k}:"), "_row_id")) for k, i in enumerate(self.inputs)]
        return tagged[0].unionByName(tagged[1])

    def at(self, version):
        return self._both(lambda i: i.at(version))

    def delta(self, v0, v1):
        return self._both(lambda i: i.delta(v0, v1))

    def strategy(self):
        return "linear"

    def insert_only(self, rules="paper"):
        return self._all_insert_only(rules)


class Join(Relation):
    """Inner join on equal columns, or on any condition over columns of different names (``true`` for all pairs). The
    change is dA with B before, and A after with dB; signs multiply."""

    def __init__(self, left: Relation, right: Relation, on: list[str] | None = None, condition: str | None = None):
        self.inputs, self.db, self.on, self.condition = (left, right), left.db, on, condition
        if on is None and condition is None:
            raise ValueError("a join needs columns or a condition")
        if on is None and (both := {c.lower() for c in left.columns} & {c.lower() for c in right.columns}):
            raise ValueError(f"columns of both sides: {sorted(both)}")

    def _join(self, a: DataFrame, b: DataFrame) -> DataFrame:
        a, b = a.withColumnRenamed("_row_id", "_left"), b.withColumnRenamed("_row_id", "_right")
        if "_sign" in a.columns and "_sign" in b.columns:
            raise ValueError("one side of a join carries signs")
        made = a.join(b, self.on) if self.on is not None else a.join(b, F.expr(self.condition))
        return made.withColumn("_row_id", F.concat_ws("|", "_left", "_right")).drop("_left", "_right")

    def at(self, version):
        return self._join(self.inputs[0].at(version), self.inputs[1].at(version))

    def delta(self, v0, v1):
        a, b = self.inputs
        names = [*(c for c in self.columns), "_row_id", "_sign"]
        parts = []
        moved = self.db.changed(v0, v1)
        if a.tables() & moved:
            parts.append(self._join(a.delta(v0, v1), b.at(v0)).select(*names))
        if b.tables() & moved:
            parts.append(self._join(a.at(v1), b.delta(v0, v1)).select(*names))
        if not parts:
            return self.at(v1).withColumn("_sign", F.lit(1)).limit(0)
        return parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])

    def strategy(self):
        return "bilinear"

    def insert_only(self, rules="paper"):
        return self._all_insert_only(rules)


class Keyed(Relation):
    """Operators whose rows of one key depend on the inputs' rows of that key alone: changed keys are recomputed."""

    keys: list[str]

    def compute(self, inputs: list[DataFrame]) -> DataFrame:
        raise NotImplementedError

    def at(self, version):
        return self.compute([i.at(version) for i in self.inputs])

    def delta(self, v0, v1):
        """The rows of the changed keys before, and those rows with the inputs' change applied: the inputs are read once,
        and only their rows of changed keys go on."""
        moved = self.db.changed(v0, v1)
        change = [consolidate(i.delta(v0, v1)) if i.tables() & moved else None for i in self.inputs]
        touched = None
        for d in change:
            if d is not None:
                keys = d.select(*self.keys)
                touched = keys if touched is None else touched.unionByName(keys)
        if touched is None:
            return self.at(v1).withColumn("_sign", F.lit(1)).limit(0)
        touched = touched.distinct()
        before = [touching(i.at(v0), touched, self.keys) for i in self.inputs]
        after = [rows if d is None else applied(rows, d) for rows, d in zip(before, change, strict=True)]
        return consolidate(self.compute(before).withColumn("_sign", F.lit(-1)).unionByName(self.compute(after).withColumn("_sign", F.lit(1))))

    def strategy(self):
        return "changed keys"


class Aggregate(Keyed):
    """Grouping; without aggregates it is DISTINCT. A global aggregate (no keys) is one group."""

    def __init__(self, child: Relation, keys: list[str], aggregates: dict[str, str]):
        self.inputs, self.db, self.keys, self.aggregates = (child,), child.db, keys, aggregates

    def compute(self, inputs):
        made = inputs[0].groupBy(*(F.col(f"`{k}`") for k in self.keys)).agg(*([F.expr(e).alias(n) for n, e in self.aggregates.items()] or [F.count("*").alias("_n")]))
        return made.drop("_n").withColumn("_row_id", key_id(self.keys))

    def insert_only(self, rules="paper"):
        return self._all_insert_only(rules) if rules == "extended" and not self.aggregates else (False, "grouping or aggregates")


class KeyedJoin(Keyed):
    """Outer, semi and anti joins on equal columns."""

    def __init__(self, left: Relation, right: Relation, on: list[str], how: str):
        self.inputs, self.db, self.keys, self.how = (left, right), left.db, on, how

    def compute(self, inputs):
        a, b = inputs[0].withColumnRenamed("_row_id", "_left"), inputs[1].withColumnRenamed("_row_id", "_right")
        out = a.join(b, self.keys, self.how)
        if "_right" not in out.columns:
            return out.withColumnRenamed("_left", "_row_id")
        return out.withColumn("_row_id", F.concat_ws("|", F.coalesce("_left", F.lit("")), F.coalesce("_right", F.lit("")))).drop("_left", "_right")

    def insert_only(self, rules="paper"):
        if rules == "extended" and self.how == "left_semi":
            return self._all_insert_only(rules)
        return False, f"{self.how} join"


class SetOperation(Keyed):
    """intersect, except or union of distinct rows, ``intersect all`` and ``except all`` of rows with their numbers; the
    key is the whole row. Equal rows of a result are told apart by a number."""

    def __init__(self, left: Relation, right: Relation, op: str):
        self.inputs, self.db, self.op = (left, right), left.db, op
        self.keys = left.columns

    def compute(self, inputs):
        a, b = (i.select(*self.keys) for i in inputs)
        ops = {"intersect": a.intersect, "except": a.subtract, "union": lambda x: a.union(x).distinct(), "intersect all": a.intersectAll, "except all": a.exceptAll}
        out = ops[self.op](b)
        if not self.op.endswith("all"):
            return out.withColumn("_row_id", key_id(self.keys))
        n = F.row_number().over(Window.partitionBy(*(F.col(f"`{k}`") for k in self.keys)).orderBy(F.lit(0)))
        return out.withColumn("_n", n).withColumn("_row_id", F.concat_ws("#", key_id(self.keys), F.col("_n").cast("string"))).drop("_n")

    def insert_only(self, rules="paper"):
        return (False, "EXCEPT") if self.op.startswith("except") else self._all_insert_only(rules)


class Ranked(Keyed):
    """An analytic function over partitions; touched partitions are recomputed."""

    def __init__(self, child: Relation, by: list[str], order: str, name: str, function: str):
        self.inputs, self.db, self.keys = (child,), child.db, by
        self.order, self.name, self.function = order, name, function

    def compute(self, inputs):
        return inputs[0].withColumn(self.name, F.expr(f"{self.function} over (partition by {', '.join(self.keys)} order by {self.order})"))


class TopK(Relation):
    """The n first rows. Candidates are the old ones, less those removed, and what was added. They are enough while n of
    them rank no lower than the old last one did, for no other row ranks higher than that; else all rows are ranked again.
    Only rows of the top, three times n at most, are held on the driver; those of the last version asked for are kept, so
    a task that follows commit by commit ranks all rows once."""

    def __init__(self, child: Relation, n: int, order: list[tuple[str, bool]]):
        self.inputs, self.db, self.n, self.order = (child,), child.db, n, order
        self.kept: tuple[int, list] | None = None

    def _sorted(self, rows: DataFrame, *more: str) -> DataFrame:
        return rows.orderBy(*(F.col(c).desc() if down else F.col(c).asc() for c, down in self.order), *more)

    def _first(self, rows: DataFrame) -> DataFrame:
        return self._sorted(rows).limit(self.n)

    def at(self, version):
        return self._first(self.inputs[0].at(version))

    def delta(self, v0, v1):
        spark, now = self.db.spark, self.at(v0)
        held = self.kept[1] if self.kept and self.kept[0] == v0 else now.collect()
        local = lambda rows: spark.createDataFrame(rows, now.schema)
        before, columns = local(held), now.columns
        change = consolidate(self.inputs[0].delta(v0, v1))
        added = self._first(change.filter("_sign > 0").drop("_sign")).withColumn("_sign", F.lit(1))
        gone = change.filter("_sign < 0").filter(F.col("_row_id").isin([r._row_id for r in held]))
        got = added.select(*columns, "_sign").unionByName(gone.select(*columns, F.col("_sign").cast("int"))).collect()
        plus = [tuple(r[:-1]) for r in got if r._sign > 0]
        minus = {r._row_id for r in got if r._sign < 0}
        stay = [tuple(r) for r in held if r._row_id not in minus]
        after = self._sorted(local([*stay, *plus]).withColumn("_last", F.lit(0)).unionByName(local(held[-1:]).withColumn("_last", F.lit(1))), "_last")
        ranked = after.collect()
        ahead = next((i for i, r in enumerate(ranked) if r._last), len(ranked))
        if len(held) < self.n or ahead >= self.n:
            top = [tuple(r[:-1]) for r in ranked if not r._last][: self.n]
        else:
            top = [tuple(r) for r in self.at(v1).collect()]
        result = local(top)
        self.kept = (v1, result.collect())
        return consolidate(before.withColumn("_sign", F.lit(-1)).unionByName(result.withColumn("_sign", F.lit(1))))

    def strategy(self):
        return "candidates"


class Sql(Relation):
    """Any query text over tables of the database; its rows have their values as identity, so equal rows are numbered."""

    def __init__(self, db: Database, text: str, names: list[str], key: list[str] | None = None):
        self.db, self.text, self.names, self.key = db, text, names, key

    def _analysed(self, version: int, use):
        """``use()`` while the tables' rows at a version stand under their names; views of the user come back after."""
        spark = self.db.spark
        held = {n: spark.table(n) for n in self.names if any(t.isTemporary and t.name == n for t in spark.catalog.listTables(pattern=n))}
        try:
            for n in self.names:
                self.db.table(n).snapshot(version).createOrReplaceTempView(n)
            return use()
        finally:
            for n in self.names:
                if n in held:
                    held[n].createOrReplaceTempView(n)
                else:
                    spark.catalog.dropTempView(n)

    def at(self, version):
        out = self._analysed(version, lambda: self.db.spark.sql(self.text))  # a query is analysed at once
        return out.withColumn("_row_id", key_id(self.key or out.columns))

    def tables(self):
        return set(self.names)

    def insert_only(self, rules="paper"):
        from standq.plans.prover import prove_insert_only

        own = {n: self.db.metas[n].insert_only for n in self.names}
        got = self._analysed(0, lambda: prove_insert_only(self.db.spark, self.text, own, rules))
        return got.ok, got.reason


class Changes(Relation):
    """The history of a relation as a relation: it only ever grows, so a log of a log is all inserts."""

    def __init__(self, child: Relation, start: int = 0, format: str = "DELTA"):  # noqa: A002
        self.inputs, self.db, self.start, self.format = (child,), child.db, start, format

    def at(self, version):
        return change_rows(self.inputs[0], self.start, version, self.format)

    def delta(self, v0, v1):
        return change_rows(self.inputs[0], max(v0, self.start), v1, self.format).withColumn("_sign", F.lit(1))

    def strategy(self):
        return "log slice"

    def insert_only(self, rules="paper"):
        return True, "R11 changes"


def net_changes(rel: Relation, v0: int, v1: int, strategy: str = "incremental") -> DataFrame:
    """Net records with images of any relation between two versions."""
    if isinstance(rel, Scan) and strategy == "incremental":
        return compact_net(rel.table.log_slice(v0, v1))
    rows = rel.difference(v0, v1) if strategy == "diff" else consolidate(rel.delta(v0, v1))
    return from_signed(rows)


def changes(rel: Relation, start: int = 0, end: int | None = None, format: str = "DELTA", encoding: str = "pair", compaction: str = "net") -> DataFrame:  # noqa: A002
    """The changes of a relation in the commits (start, end].

    LOG gives every operation of a table; of a query, the net change of each commit. DELTA consolidates the whole range:
    ``net`` or ``pattern`` (see compactions). Encodings: ``pair``, ``single``, ``delete_insert``.
    """
    end = rel.db.version if end is None else end
    if format == "LOG":
        if isinstance(rel, Scan):
            return encode(rel.table.log_slice(start, end), encoding)
        return encode(per_commit_changes(rel, start, end), encoding)
    if isinstance(rel, Scan) and compaction == "pattern":
        return encode(compact_update(rel.table.log_slice(start, end)), encoding)
    return encode(net_changes(rel, start, end), encoding)


CAST = re.compile(r"\s*cast\s*\((.*)\s+as\s+[\w() ,]+\)\s*", re.I | re.S)
CALL = re.compile(r"\s*(sum|count|min|max)\s*\((.*)\)\s*", re.I | re.S)


def plain_call(text: str) -> re.Match | None:
    """A single aggregate that partial ones make up, maybe in a cast."""
    inner = m[1] if (m := CAST.fullmatch(text)) and balanced(m[1]) else text
    m = CALL.fullmatch(inner)
    return m if m and balanced(m[2]) and not re.match(r"\s*distinct\b", m[2], re.I) else None


def running_commits(rel: Relation, start: int, end: int) -> DataFrame | None:
    """The net change of every commit of a grouping over rows that were only ever added, in one plan whatever the number
    of commits: partial aggregates by key and commit, then running ones in each key. None where that is not the case."""
    chain, node = [], rel.inputs[0] if isinstance(rel, Aggregate) and rel.aggregates else None
    while isinstance(node, Linear):
        chain, node = [node, *chain], node.inputs[0]
    if not isinstance(node, Scan) or not node.table.only_inserts(end):
        return None
    calls = {n: plain_call(e) for n, e in rel.aggregates.items()}
    if not all(calls.values()):
        return None
    rows = node.table.log_slice(0, end).select(*node.table.columns, "_row_id", F.greatest(F.col("_commit_no"), F.lit(start)).alias("_commit_no"))
    for step in chain:
        rows = step.map(rows)
    kinds = {f.name: f.dataType for f in rel.at(0).schema.fields}
    merge = {"sum": F.sum, "count": F.sum, "min": F.min, "max": F.max}
    per = rows.groupBy(*(F.col(f"`{k}`") for k in rel.keys), "_commit_no").agg(*(F.expr(f"{m[1]}({m[2]})").alias(n) for n, m in calls.items()))
    by = Window.partitionBy(*(F.col(f"`{k}`") for k in rel.keys)).orderBy("_commit_no")
    sofar = by.rowsBetween(Window.unboundedPreceding, 0)
    run = per.select(*(F.col(f"`{k}`") for k in rel.keys), "_commit_no", *(merge[m[1].lower()](F.col(f"`{n}`")).over(sofar).cast(kinds[n]).alias(n) for n, m in calls.items()))
    values = [*rel.keys, *rel.aggregates]
    image = F.struct(*(F.col(f"`{c}`") for c in values))
    made = run.withColumn("_before", F.lag(image).over(by)).filter(F.col("_commit_no") > start)
    made = made.filter(F.col("_before").isNull() | ~F.col("_before").eqNullSafe(image))
    action = F.when(F.col("_before").isNull(), "INSERT").otherwise("UPDATE").alias("_action")
    return made.select(
        *(F.col(f"`{c}`") for c in values), action, key_id(rel.keys).alias("_row_id"), "_before",
        F.lit(None).cast("timestamp_ntz").alias("_time"), "_commit_no", F.lit(0).cast("long").alias("_seq"),
    )


def balanced(text: str) -> bool:
    depth = 0
    for c in text:
        depth += (c == "(") - (c == ")")
        if depth < 0:
            return False
    return depth == 0


def per_commit_changes(rel: Relation, start: int, end: int) -> DataFrame:
    if isinstance(rel, Aggregate) and rel.keys and (made := running_commits(rel, start, end)) is not None:
        return made
    out = None
    for v in range(start, end):
        if not rel.tables() & rel.db.changed(v, v + 1):
            continue
        part = net_changes(rel, v, v + 1)
        if "_commit_no" not in part.columns:
            part = part.withColumn("_time", F.lit(None).cast("timestamp_ntz")).withColumn("_commit_no", F.lit(v + 1).cast("long")).withColumn("_seq", F.lit(0).cast("long"))
        out = part if out is None else out.unionByName(part)
    return net_changes(rel, start, start) if out is None else out


def change_rows(rel: Relation, start: int, end: int, format: str) -> DataFrame:  # noqa: A002
    """Changes with visible columns action, row_id, commit_no, seq instead of the hidden ones (numbered where a log of a
    log has them already), and a row id of their own."""
    made = rel.table.log_slice(start, end) if isinstance(rel, Scan) and format == "LOG" else per_commit_changes(rel, start, end)
    values = value_columns(made)
    depth = 1 + sum(c == "action" or c.startswith("action_") for c in values)
    name = lambda c: c if depth == 1 else f"{c}_{depth}"
    shown = {c: name(c) for c in ("action", "row_id", "commit_no", "seq")}
    out = made.select(*(F.col(f"`{c}`") for c in values), *(F.col(f"_{c}").alias(n) for c, n in shown.items()))
    return out.withColumn("_row_id", key_id([shown[c] for c in ("row_id", "commit_no", "seq", "action")], "c"))


@dataclass
class Simplified:
    rel: Relation
    notes: list[str] = field(default_factory=list)


def simplify(rel: Relation) -> Simplified:
    """CHANGES over an insert-only table may be left out: its rows are the table's, if nothing else ever happened to them
    and they are asked for from the beginning."""
    if isinstance(rel, Changes) and isinstance(rel.inputs[0], Scan) and not rel.start and rel.inputs[0].table.meta.insert_only and rel.inputs[0].table.only_inserts(rel.db.version):
        return Simplified(rel.inputs[0], ["changes of an insert-only table is the table"])
    return Simplified(rel)


__all__ = ["Aggregate", "Changes", "Filter", "Join", "Project", "Relation", "Scan", "SetOperation", "Sql", "TopK", "UnionAll", "WindowTable", "changes", "net_changes", "simplify"]

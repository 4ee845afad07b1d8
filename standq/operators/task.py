"""Continuous DML: tasks with schedules, error handling, states, and exactly-once bookmarks."""

from __future__ import annotations

import threading
import uuid
from collections.abc import Callable
from dataclasses import dataclass, field, replace
from datetime import datetime, timedelta
from typing import Any

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from standq.errors import ConcurrentCommit, ConstraintViolation, IllegalTransition, NotInsertOnly, RejectLimit, StandingQueryError
from standq.functions.compaction import compact_delete_insert, compact_update, value_columns
from standq.plans.relation import Relation, Scan, net_changes
from standq.sources.store import Database, row_ids

# Schedules


@dataclass(frozen=True)
class Schedule:
    ends: datetime | None = None
    most: int | None = None

    def until(self, when: datetime) -> Schedule:
        return replace(self, ends=when)

    def times(self, n: int) -> Schedule:
        return replace(self, most=n)

    def __or__(self, other: Schedule) -> Either:
        return Either(parts=(self, other))

    def on_commit(self, tables: set[str]) -> str | None:
        """``sync``, ``async`` or None for a commit that touches ``tables``."""
        return None

    def due(self, last: datetime, now: datetime) -> bool:
        return False


@dataclass(frozen=True)
class OnCommit(Schedule):
    asynchronous: bool = False
    tables: tuple[str, ...] | None = None

    def on_commit(self, tables):
        if self.tables is not None and not tables & set(self.tables):
            return None
        return "async" if self.asynchronous else "sync"


@dataclass(frozen=True)
class Every(Schedule):
    seconds: float = 60.0

    def due(self, last, now):
        return now - last >= timedelta(seconds=self.seconds)


@dataclass(frozen=True)
class Cron(Schedule):
    """minute hour day month weekday; each a star, a number, a list or a step (``*/5``)."""

    text: str = "* * * * *"

    def _matches(self, t: datetime) -> bool:
        def one(part: str, v: int) -> bool:
            return any(p == "*" or (p.startswith("*/") and v % int(p[2:]) == 0) or (p.isdigit() and int(p) == v) for p in part.split(","))

        return all(one(p, v) for p, v in zip(self.text.split(), (t.minute, t.hour, t.day, t.month, (t.weekday() + 1) % 7), strict=True))

    def due(self, last, now):
        t = last.replace(second=0, microsecond=0) + timedelta(minutes=1)
        steps = 0
        while t <= now and steps < 527_040:  # a year of minutes
            if self._matches(t):
                return True
            t, steps = t + timedelta(minutes=1), steps + 1
        return False


@dataclass(frozen=True)
class OnDemand(Schedule):
    pass


@dataclass(frozen=True)
class Either(Schedule):
    parts: tuple[Schedule, ...] = ()

    def on_commit(self, tables):
        found = [m for p in self.parts if (m := p.on_commit(tables))]
        return "sync" if "sync" in found else found[0] if found else None

    def due(self, last, now):
        return any(p.due(last, now) for p in self.parts)


class Scheduler:
    """Fires what is due: on commits at once (or queued, if asynchronous), on time at ``tick``. ``start`` makes a thread
    tick by itself; it also sees the commits of other sessions. Runs of one task never overlap: in a process they are told
    apart here, between processes by the task's lease."""

    _of: dict[int, Scheduler] = {}

    def __init__(self, db: Database):
        self.db, self.members, self.queue, self.last, self.runs, self.busy = db, [], [], {}, {}, set()
        self.seen, self.lock, self.thread, self.halt = db.version, threading.RLock(), None, threading.Event()
        self.failed: list[tuple[str, Exception]] = []
        db.listeners.append(self._committed)

    @classmethod
    def of(cls, db: Database) -> Scheduler:
        if id(db) not in cls._of or cls._of[id(db)].db is not db:
            cls._of[id(db)] = cls(db)
        return cls._of[id(db)]

    def add(self, member: Any) -> None:
        self.members.append(member)
        self.last[member.name], self.runs[member.name] = self.db.clock.now(), 0

    def remove(self, member: Any) -> None:
        self.members = [m for m in self.members if m is not member]

    def _fire(self, m: Any) -> None:
        s = m.schedule
        if m.name in self.busy or (s.most is not None and self.runs[m.name] >= s.most) or (s.ends is not None and self.db.clock.now() > s.ends):
            return
        self.busy.add(m.name)
        try:
            m.run_now()
            self.runs[m.name] += 1
            self.last[m.name] = self.db.clock.now()
        finally:
            self.busy.discard(m.name)

    def _committed(self, manifest: dict[str, Any]) -> None:
        """Take every commit up to this one in turn, those of other sessions too."""
        with self.lock:
            while self.seen < manifest["commit"]:
                self.seen += 1
                self._told(self.db.manifests[self.seen - 1])

    def _told(self, manifest: dict[str, Any]) -> None:
        tables = set(manifest["tables"])
        for m in list(self.members):
            if tables & m.sources() and (how := m.schedule.on_commit(tables)):
                if how == "sync":
                    self._fire(m)
                elif m not in self.queue:
                    self.queue.append(m)

    def tick(self) -> int:
        """Run what is queued and what time has made due; returns how many ran."""
        with self.lock:
            if self.db.refresh() > self.seen:
                self._committed(self.db.manifests[-1])
            waiting, self.queue = self.queue, []
            now = self.db.clock.now()
            ready = [*waiting, *(m for m in self.members if m not in waiting and m.schedule.due(self.last[m.name], now))]
            for m in ready:
                self._fire(m)
            return len(ready)

    def start(self, every: float = 1.0) -> None:
        """Tick every so many seconds in a thread, until ``stop``. An error of a run is kept in ``failed`` and does not end
        the thread; the task's bookmark stays, so its next run tries again."""
        if self.thread is not None:
            return
        self.halt.clear()

        def work() -> None:
            while not self.halt.wait(every):
                try:
                    self.tick()
                except Exception as e:
                    self.failed.append((type(e).__name__, e))

        self.thread = threading.Thread(target=work, name="standq-scheduler", daemon=True)
        self.thread.start()

    def stop(self) -> None:
        self.halt.set()
        if self.thread is not None:
            self.thread.join()
            self.thread = None


class Lease:
    """A file that one run of a task holds in the shared log; others pass meanwhile. It lapses after ``seconds``, so a
    driver that was lost does not hold it for ever; should two runs overlap then, only one of their commits counts."""

    def __init__(self, db: Database, name: str, seconds: float = 3600.0):
        self.db, self.file, self.seconds, self.mark = db, f"_leases/{name}.json", seconds, uuid.uuid4().hex

    def take(self) -> bool:
        for _ in range(2):
            now = self.db.clock.now()
            try:
                self.db.log.put(self.file, {"until": now + timedelta(seconds=self.seconds), "mark": self.mark})
                return True
            except ConcurrentCommit:
                held = self.db.log.get(self.file)
                if held and datetime.fromisoformat(held["until"]) > now:
                    return False
                self.db.log.delete(self.file)
        return False

    def free(self) -> None:
        held = self.db.log.get(self.file)
        if held and held["mark"] == self.mark:
            self.db.log.delete(self.file)


# Errors


@dataclass
class ErrorPolicy:
    """Rows that break the target's checks go to ``log_table`` (columns tag, reason, row as JSON), up to ``reject_limit``
    a run; beyond that the run fails and is tried again up to ``retry_limit`` times; the bookmark then stays."""

    log_table: str | None = None
    tag: str = ""
    reject_limit: int | None = 0
    retry_limit: int = 0


# States

TRANSITIONS = {
    ("ACTIVE", "pause"): "PAUSED",
    ("ACTIVE", "stop"): "STOPPED",
    ("PAUSED", "resume"): "ACTIVE",
    ("PAUSED", "stop"): "STOPPED",
    ("STOPPED", "resume"): "ACTIVE",
}


@dataclass
class Task:
    """A named statement that takes what changed in its source since the last run and brings its target up to it.

    Kinds: ``insert`` appends the rows of an insert-only source; ``merge`` joins changes to the target by columns;
    ``apply`` brings the target in step with any query; ``statement`` runs a plain statement each time (a baseline).
    The bookmark is in the manifest of the commit that holds the changes, so a run counts once or not at all.
    """

    db: Database
    name: str
    kind: str
    source: Relation
    target: str
    schedule: Schedule = field(default_factory=OnCommit)
    errors: ErrorPolicy = field(default_factory=ErrorPolicy)
    columns: dict[str, str] | None = None
    on: list[str] = field(default_factory=list)
    set_: dict[str, str] = field(default_factory=dict)
    delete_where: str = "_action = 'DELETE'"
    insert_values: dict[str, str] = field(default_factory=dict)
    ordered: str | None = None
    initial_snapshot: bool = False
    strategy: str = "incremental"
    statement: Callable[[Any], None] | None = None
    callbacks: list[Callable[[DataFrame], None]] = field(default_factory=list)

    def __post_init__(self):
        if self.kind == "insert":
            ok, why = self.source.insert_only("extended")
            if not ok:
                raise NotInsertOnly(why)
        kept = self.db.log.get(self._file)
        if kept is None:
            self.state, self.base = "ACTIVE", self.db.version
            self._save()
            if self.initial_snapshot:
                self._run(0, self.base)
        else:
            self.state, self.base = kept["state"], kept["base"]
        Scheduler.of(self.db).add(self)

    @property
    def _file(self) -> str:
        return f"_tasks/{self.name}.json"

    def _save(self) -> None:
        self.db.log.replace(self._file, {"state": self.state, "base": self.base, "kind": self.kind, "target": self.target})

    @property
    def bookmark(self) -> int:
        """The last source commit applied, from the manifests; the start where there is none since."""
        return max([self.base, *(m["bookmarks"][self.name] for m in self.db.manifests if self.name in m["bookmarks"])])

    def sources(self) -> set[str]:
        return self.source.tables()

    def alter(self, event: str) -> str:
        """pause, resume or stop. What was missed while paused is caught up; what was missed while stopped is skipped."""
        to = TRANSITIONS.get((self.state, event))
        if to is None:
            raise IllegalTransition(f"{self.name}: {event} while {self.state}")
        if self.state == "STOPPED":
            self.base = self.db.version
        self.state = to
        self._save()
        return to

    def drop(self) -> None:
        Scheduler.of(self.db).remove(self)
        self.db.log.delete(self._file)

    def run_now(self) -> int | None:
        """One run; returns the commit made, or None if there was nothing to do, the task is not active, or another
        process runs it."""
        if self.state != "ACTIVE":
            return None
        lease = Lease(self.db, self.name)
        if not lease.take():
            return None
        try:
            return self._try()
        finally:
            lease.free()

    def _try(self) -> int | None:
        self.db.refresh()
        if self.kind == "statement":
            return self._run(0, self.db.version)
        after, upto = self.bookmark, self.db.version
        if not self.sources() & self.db.changed(after, upto):
            return None
        for attempt in range(self.errors.retry_limit + 1):
            try:
                return self._run(after, upto)
            except (RejectLimit, ConcurrentCommit):
                if attempt == self.errors.retry_limit:
                    raise
                upto = self.db.refresh()
        return None

    def _run(self, after: int, upto: int) -> int | None:
        from standq.sources.store import Transaction

        tx = Transaction(self.db)
        try:
            if self.kind == "statement":
                self.statement(tx)
                return tx.commit()
            made = self._changes(after, upto)
            if self.db.metas[self.target].checks:
                made = self._reject(tx, made)
            tx.apply(self.target, made)
            tx.bookmarks[self.name] = upto
            number = tx.commit()
        except BaseException:
            if not tx.done:
                tx.abort()
            raise
        for told in self.callbacks:
            told(self.db.table(self.target).log_slice(number - 1, number))
        return number

    def _changes(self, after: int, upto: int) -> DataFrame:
        schema = self.db.table(self.target).schema
        names = schema.fieldNames()
        if self.kind == "insert":
            rows = self.source.at(upto) if after == 0 else self.source.delta(after, upto).drop("_sign")
            rows = rows.select(*((F.expr(self.columns[n]) if self.columns and n in self.columns else F.col(n)).alias(n) for n in names), "_row_id")
            return rows.withColumn("_action", F.lit("INSERT")).withColumn("_before", F.lit(None).cast(schema))
        if self.kind == "merge":
            return self._merge(after, upto, schema)
        net = net_changes(self.source, after, upto, self.strategy)
        own = F.struct(*(F.col("_before")[n].cast(schema[n].dataType).alias(n) for n in names))
        return net.select(*(F.col(n).cast(schema[n].dataType).alias(n) for n in names), "_action", "_row_id", F.when(F.col("_before").isNotNull(), own).alias("_before"))

    def _merge(self, after: int, upto: int, schema) -> DataFrame:
        """Match the compacted changes with the target by ``on``: update, or delete where ``delete_where`` holds; insert
        what does not match and is not deleted."""
        if self.ordered and isinstance(self.source, Scan):
            from standq.functions.compaction import encode

            log = self.source.table.log_slice(after, upto)
            made = compact_update(log) if self.ordered == "update" else compact_delete_insert(encode(log, "delete_insert"))
        else:
            made = net_changes(self.source, after, upto)
        names = schema.fieldNames()
        source = made.select(*(F.col(f"`{c}`").alias(f"s_{c}") for c in value_columns(made)), F.col("_action").alias("_a"), F.col("_row_id").alias("_s"))
        target = self.db.table(self.target).snapshot(upto, with_id=True)
        target = target.select(*(F.col(f"`{c}`").alias(f"t_{c}") for c in names), F.col("_row_id").alias("_t"))
        on: Column = F.lit(True)
        for c in self.on:
            on = on & (F.col(f"s_{c}") == F.col(f"t_{c}"))
        both = source.join(target, on, "left")
        twice = both.filter(F.col("_t").isNotNull()).groupBy("_t").agg(F.count("*").alias("n")).filter("n > 1")
        if not twice.isEmpty():
            raise ConstraintViolation(f"{self.name}: two source rows match one row of {self.target} by {self.on}")
        gone = F.expr(self.delete_where.replace("_action", "_a"))
        matched = F.col("_t").isNotNull()
        action = F.when(matched & gone, "DELETE").when(matched, "UPDATE").when(~gone, "INSERT")
        value = lambda n: F.when(
            matched & gone, F.col(f"t_{n}")
        ).when(matched, F.expr(self.set_[n]) if n in self.set_ else F.col(f"t_{n}")).otherwise(F.expr(self.insert_values.get(n, f"s_{n}")))
        before = F.when(matched, F.struct(*(F.col(f"t_{n}").alias(n) for n in names)))
        fresh = row_ids(F.lit(upto), F.lit(0))
        return both.select(*(value(n).cast(schema[n].dataType).alias(n) for n in names), action.alias("_action"), F.coalesce("_t", F.concat(F.lit("m"), fresh)).alias("_row_id"), before.alias("_before")).filter("_action is not null")

    def _reject(self, tx, made: DataFrame) -> DataFrame:
        good: Column = F.lit(True)
        for c in self.db.metas[self.target].checks:
            good = good & F.coalesce(F.expr(c), F.lit(True))
        good = good | (F.col("_action") == "DELETE")
        bad = made.filter(~good)
        n = bad.count()
        if n and (self.errors.log_table is None or (self.errors.reject_limit is not None and n > self.errors.reject_limit)):
            raise RejectLimit(f"{self.name}: {n} rows rejected")
        if n:
            names = self.db.table(self.target).columns
            reason = F.lit("; ".join(self.db.metas[self.target].checks))
            tx.insert(self.errors.log_table, bad.select(F.lit(self.errors.tag).alias("tag"), reason.alias("reason"), F.to_json(F.struct(*names)).alias("row_json")))
        return made.filter(good)

    # constructors
    @classmethod
    def insert(cls, db, name, source, target, **options) -> Task:
        return cls(db, name, "insert", source, target, **options)

    @classmethod
    def merge(cls, db, name, source, target, on, set_, **options) -> Task:
        return cls(db, name, "merge", source, target, on=on, set_=set_, **options)

    @classmethod
    def apply_changes(cls, db, name, source, target, **options) -> Task:
        return cls(db, name, "apply", source, target, **options)


def create_target(db: Database, name: str, source: Relation, insert_only: bool = False) -> None:
    schema = source.to_df(0).schema
    db.create_table(name, schema, insert_only=insert_only)


def keep_in_sync(db: Database, target: str, source: Relation, strategy: str = "auto", name: str | None = None, schedule: Schedule | None = None) -> Task:
    """A target that follows a query. ``full`` replaces all rows each time, ``diff`` compares two versions, ``incremental``
    derives the change, ``auto`` appends where the source is proven insert-only and derives otherwise."""
    name = name or f"sync_{target}"
    if strategy == "full":

        def statement(tx):
            tx.delete(target)
            tx.insert(target, source.to_df(tx.number - 1))

        return Task(db, name, "statement", source, target, schedule=schedule or OnCommit(), statement=statement)
    kind = "insert" if strategy == "auto" and source.insert_only("extended")[0] else "apply"
    way = "diff" if strategy == "diff" else "incremental"
    return Task(db, name, kind, source, target, schedule=schedule or OnCommit(), strategy=way, initial_snapshot=True)


@dataclass
class View:
    """An insertable view: column names over a table's, and a condition that inserted rows must hold."""

    db: Database
    table: str
    columns: dict[str, str]
    where: str | None = None

    def to_base(self, rows: DataFrame) -> DataFrame:
        schema = self.db.table(self.table).schema
        back = {base: seen for seen, base in self.columns.items()}
        out = rows.select(*((F.col(back[f.name]) if f.name in back else F.lit(None)).cast(f.dataType).alias(f.name) for f in schema.fields))
        if self.where and not out.filter(~F.coalesce(F.expr(self.where), F.lit(False))).limit(1).isEmpty():
            raise StandingQueryError(f"rows outside the view: {self.where}")
        return out

    def insert(self, tx, rows: DataFrame) -> int:
        return tx.insert(self.table, self.to_base(rows))


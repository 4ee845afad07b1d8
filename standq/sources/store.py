"""Versioned tables: an append-only change log in Parquet, one manifest a commit, snapshots folded from the log.

A change record has the table's columns (the row after the change; for a delete the row before it) and

* ``_action``: INSERT, UPDATE or DELETE
* ``_row_id``: identity of the row through its life, never used again
* ``_before``: the row before an update or delete, else null
* ``_time``: when the statement ran (information only)
* ``_commit_no``, ``_seq``: the order of history: commit, and statement in it

Bookmarks are commit numbers. A manifest makes the changes of all tables of a transaction, and the bookmarks of the task
that ran it, visible at once or not at all.
"""

from __future__ import annotations

import json
import uuid
from collections.abc import Callable
from contextlib import contextmanager
from dataclasses import asdict, dataclass, field
from datetime import date, datetime
from decimal import Decimal
from typing import Any

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from standq.clock import SystemClock
from standq.errors import ConcurrentCommit, ConstraintViolation, Dependent, StandingQueryError
from standq.operators.constraints import Increasing, Late, check_increasing, check_increasing_by
from standq.sources.logstore import LogStore

#: Commits between two files that hold all manifests so far.
GATHER = 100


@dataclass
class Meta:
    """Properties of a table; kept in the catalog."""

    name: str
    schema: str
    key: list[str] = field(default_factory=list)
    insert_only: bool = False
    increasing: dict[str, dict[str, Any]] = field(default_factory=dict)
    finalize: str | None = None
    expire: str | None = None
    purged: list[dict[str, Any]] = field(default_factory=list)
    snapshots: dict[str, str] = field(default_factory=dict)
    checks: list[str] = field(default_factory=list)
    since: int = 0  # commits before the table was made are not its own


#: Types of columns whose extremes each commit notes, whether they are constrained or not.
TIMES = ("date", "timestamp", "timestamp_ntz")


def parse_value(text: str, like: str) -> Any:
    """A value of a manifest back from its text."""
    if like == "date":
        return date.fromisoformat(text)
    if like in TIMES:
        return datetime.fromisoformat(text)
    if like.startswith("decimal"):
        return Decimal(text)
    return int(text) if like in ("tinyint", "smallint", "int", "bigint") else float(text) if like in ("float", "double") else text


def log_schema(schema: T.StructType) -> T.StructType:
    return T.StructType(
        [
            *schema.fields, T.StructField("_action", T.StringType()), T.StructField("_row_id", T.StringType()), T.StructField("_before", schema),
            T.StructField("_time", T.TimestampNTZType()), T.StructField("_commit_no", T.LongType()), T.StructField("_seq", T.LongType()),
        ]
    )


class Database:
    """Tables, cursors and tasks that share one sequence of commits under ``root``."""

    def __init__(self, spark: SparkSession, root: str, clock: Any = None):
        self.spark, self.root, self.clock = spark, root.rstrip("/"), clock or SystemClock()
        self.log = LogStore(spark, self.root)
        self.metas: dict[str, Meta] = {}
        self.catalog = 0
        self.manifests: list[dict[str, Any]] = []
        self.listeners: list[Callable[[dict[str, Any]], None]] = []
        self.cursors: dict[str, set[str]] = {}
        self.refresh()

    def refresh(self) -> int:
        """Read the catalog and the manifests that came since; returns the last commit number. A fresh handle starts from
        the last file that holds many manifests together. Maxima of increasing columns follow from the manifests, so all
        handles have the same."""
        kept = self.log.latest("_catalog", self.catalog)
        if kept:
            self.catalog, tables = kept
            self.metas = {k: Meta(**v) for k, v in tables.items()}
        known = 0 if kept else len(self.manifests)
        if not self.manifests:
            self.manifests = self.log.get("_manifests.json") or []
        while (m := self.log.get(f"_manifest/{len(self.manifests) + 1:020d}.json")) is not None:
            self.manifests.append(m)
        for m in self.manifests[known:]:
            self._advance(m)
        return len(self.manifests)

    def _advance(self, manifest: dict[str, Any]) -> None:
        for name, entry in manifest["tables"].items():
            meta = self.metas.get(name)
            if meta is None or manifest["commit"] <= meta.since:
                continue
            for c, state in meta.increasing.items():
                top = entry["stats"].get(c, [None, None])[1]
                if top not in (None, "None"):
                    Increasing.advance(state, parse_value(top, Table(self, name).schema[c].dataType.simpleString()))

    def gather_manifests(self) -> None:
        self.log.replace("_manifests.json", self.manifests)

    @property
    def version(self) -> int:
        return len(self.manifests)

    def changed(self, after: int, upto: int) -> set[str]:
        """Tables that the commits in (after, upto] touch."""
        return {t for m in self.manifests[after:upto] for t in m["tables"]}

    def rel(self, name: str):
        from standq.plans.relation import Scan

        return Scan(self.table(name))

    def save(self) -> None:
        """A new version of the catalog; fails if another session has made one meanwhile."""
        try:
            self.log.put(f"_catalog/{self.catalog + 1:020d}.json", {k: asdict(v) for k, v in self.metas.items()})
        except ConcurrentCommit:
            self.refresh()
            raise
        self.catalog += 1

    def create_table(
        self,
        name: str,
        schema: T.StructType | str,
        key: list[str] | None = None,
        insert_only: bool = False,
        increasing: list[Increasing] | None = None,
        finalize: str | None = None,
        expire: str | None = None,
        checks: list[str] | None = None,
    ) -> Table:
        """Metadata only. Names that begin with an underscore are the engine's own."""
        self.refresh()
        if name in self.metas:
            raise StandingQueryError(f"table {name} exists")
        if isinstance(schema, str):
            schema = T._parse_datatype_string(schema)
        if bad := [c for c in schema.fieldNames() if c.startswith("_")]:
            raise StandingQueryError(f"reserved column names: {bad}")
        if finalize or expire:
            from standq.plans.prover import require_monotone

            for predicate in (finalize, expire):
                if predicate:
                    require_monotone(predicate)
        self.metas[name] = Meta(name, schema.json(), list(key or []), insert_only, {c.column: c.state() for c in increasing or []}, finalize, expire, checks=list(checks or []), since=self.version)
        self.save()
        return Table(self, name)

    def table(self, name: str) -> Table:
        if name not in self.metas:
            raise StandingQueryError(f"no table {name}")
        return Table(self, name)

    def drop_table(self, name: str) -> None:
        self.require_no_cursor(name)
        del self.metas[name]
        self.save()

    def require_no_cursor(self, name: str) -> None:
        if open_ := [c for c, tables in self.cursors.items() if name in tables]:
            raise Dependent(f"cursors {open_} depend on {name}")

    @contextmanager
    def transaction(self):
        """All statements in the block commit together; an error leaves nothing behind, files included."""
        tx = Transaction(self)
        try:
            yield tx
            tx.commit()
        except BaseException:
            if not tx.done:
                tx.abort()
            raise

    def publish(self, manifest: dict[str, Any], then: Callable[[], None] | None = None) -> int:
        """Make a commit visible, advance the maxima, and only then wake what waits for commits."""
        number = manifest["commit"]
        self.log.put(f"_manifest/{number:020d}.json", manifest)
        self.manifests.append(manifest)
        self._advance(manifest)
        if number % GATHER == 0:
            self.gather_manifests()
        if then:
            then()
        for told in list(self.listeners):
            told(manifest)
        return number

    def ingest_history(self, name: str, rows: DataFrame, commit_no: Column, first: int | None = None) -> list[int]:
        """Load rows of an insert-only history in one job: one commit for each value of ``commit_no`` (1, 2, ..).

        Constraints are checked commit by commit against the statistics the job reports, before anything is visible.
        """
        table, base = self.table(name), self.version
        meta = table.meta
        if any(st.get("by") for st in meta.increasing.values()):
            raise StandingQueryError("histories with maxima by key are loaded by transactions")
        place = f"{self.root}/data/{name}/ins-{uuid.uuid4().hex}"
        own = [F.col(f"`{c}`") for c in table.columns]
        now = F.lit(self.clock.now()).cast("timestamp_ntz")
        # files of a commit as large as Spark's advisory size says, whatever the number of its rows
        dealt = rows.select(*own, commit_no.cast("long").alias("_n")).hint("rebalance", "_n")
        dealt.select(
            *own, F.lit("INSERT").alias("_action"), row_ids(F.col("_n") + base, F.lit(0)).alias("_row_id"), F.lit(None).cast(table.schema).alias("_before"),
            now.alias("_time"), (F.col("_n") + base).alias("_commit_no"), F.lit(0).cast("long").alias("_seq"), F.col("_n").alias("part"),
        ).write.partitionBy("part").parquet(place)
        written = self.spark.read.parquet(place)
        tracked = table.noted()
        measures = [f(F.col(f"`{c}`")).cast("string").alias(f"{k}_{c}") for c in tracked for k, f in (("min", F.min), ("max", F.max))]
        stats = written.groupBy("part").agg(F.count("*").alias("n"), *measures).orderBy("part").collect()  # one row a commit
        out = []
        for r in stats:
            for c in meta.increasing:
                low = r[f"min_{c}"]
                check_increasing(meta.increasing[c], None if low is None else parse_value(low, table.schema[c].dataType.simpleString()), c)
            entry = {"files": [f"{place}/part={r.part}"], "inserts": r.n, "updates": 0, "deletes": 0, "stats": {c: [str(r[f"min_{c}"]), str(r[f"max_{c}"])] for c in tracked}}
            out.append(self.publish({"commit": self.version + 1, "time": self.clock.now(), "tables": {name: entry}, "bookmarks": {}}))
        return out


def row_ids(commit: Column, seq: Column) -> Column:
    """Commit, statement and the row's place in the job that writes it: unique and never used again, whatever the row
    holds, so rows of one key stay apart."""
    return F.concat_ws("-", commit.cast("string"), seq.cast("string"), F.monotonically_increasing_id().cast("string"))


class Table:
    """A handle; all state is in the database."""

    def __init__(self, db: Database, name: str):
        self.db, self.name = db, name

    @property
    def meta(self) -> Meta:
        return self.db.metas[self.name]

    @property
    def schema(self) -> T.StructType:
        return T.StructType.fromJson(json.loads(self.meta.schema))

    @property
    def columns(self) -> list[str]:
        return self.schema.fieldNames()

    def noted(self) -> list[str]:
        """Columns whose extremes each commit notes: constrained ones and times."""
        times = [f.name for f in self.schema.fields if f.dataType.simpleString() in TIMES]
        return list(dict.fromkeys([*(c for c, s in self.meta.increasing.items() if s["enabled"]), *times]))

    def files(self, after: int, upto: int) -> list[str]:
        after = max(after, self.meta.since)
        return list(dict.fromkeys(f for m in self.db.manifests[after:upto] for f in m["tables"].get(self.name, {}).get("files", [])))

    def log_slice(self, after: int = 0, upto: int | None = None) -> DataFrame:
        """Change records of commits in (after, upto]; only their files are listed and read."""
        upto = self.db.version if upto is None else upto
        files, kind = self.files(after, upto), log_schema(self.schema)
        if not files:
            return self.db.spark.createDataFrame([], kind)
        rows = self.db.spark.read.schema(kind).parquet(*files)
        if any(m["tables"].get(self.name, {}).get("merged") for m in self.db.manifests[after:upto]):
            rows = rows.filter((F.col("_commit_no") > after) & (F.col("_commit_no") <= upto))
        return rows

    def merge_files(self, after: int, upto: int) -> int:
        """Many small commits in few files: the records of (after, upto] are written together in order of commit, and all
        those commits point to them. Slices still give the same rows, by the commit number in the records."""
        rows = self.log_slice(after, upto)
        path = f"{self.db.root}/data/{self.name}/merged-{after}-{upto}-{uuid.uuid4().hex}"
        rows.repartitionByRange("_commit_no").sortWithinPartitions("_commit_no").write.parquet(path)
        n = 0
        for m in self.db.manifests[after:upto]:
            if self.name in m["tables"] and m["tables"][self.name]["files"]:
                m["tables"][self.name] |= {"files": [path], "merged": True}
                self.db.log.replace(f"_manifest/{m['commit']:020d}.json", m)
                n += 1
        self.db.gather_manifests()
        return n

    def only_inserts(self, upto: int, after: int = 0) -> bool:
        """Whether the commits (after, upto] added rows and did nothing else."""
        own = (m["tables"].get(self.name, {}) for m in self.db.manifests[max(after, self.meta.since) : upto])
        return not any(e.get("updates") or e.get("deletes") for e in own)

    def snapshot(self, version: int | None = None, pending: list[str] | None = None, with_id: bool = False) -> DataFrame:
        """Rows at a version.

        Files of fresh rows (and the newest folded snapshot) are scanned as they are, less the rows that updates and
        deletes name; of those the last record counts. So only records of changes are grouped, and inserted rows move
        only if the changes are too many for a broadcast.
        """
        upto = self.db.version if version is None else version
        names = [*self.columns, *(["_row_id"] if with_id else [])]
        kind, spark = log_schema(self.schema), self.db.spark
        folded = max((int(v) for v in self.meta.snapshots if int(v) <= upto), default=0)
        if not pending and not folded and self.only_inserts(upto):
            return self.log_slice(0, upto).select(*(F.col(f"`{c}`") for c in names))
        files = [*self.files(folded, upto), *(pending or [])]
        fresh, changed = [f for f in files if "/ins-" in f], [f for f in files if "/ins-" not in f]
        fresh += [self.meta.snapshots[str(folded)]] if folded else []
        log = spark.read.schema(kind).parquet(*changed) if changed else None
        if log is not None and any(m["tables"].get(self.name, {}).get("merged") for m in self.db.manifests[folded:upto]):
            log = log.filter(F.col("_commit_no").between(folded + 1, upto + bool(pending)))
        own = [F.col(f"`{c}`") for c in names]
        base = spark.read.schema(kind).parquet(*fresh).select(*(F.col(f"`{c}`") for c in self.columns), "_row_id") if fresh else None
        if log is None:
            return (base if base is not None else spark.createDataFrame([], kind)).select(*own)
        row = F.struct(*(F.col(f"`{c}`") for c in self.columns), "_action")
        last = log.groupBy("_row_id").agg(F.max_by(row, F.struct("_commit_no", "_seq")).alias("r"))
        last = last.filter("r._action <> 'DELETE'").select("r.*", "_row_id").select(*own)
        if base is None:
            return last
        return base.join(log.select("_row_id"), "_row_id", "left_anti").select(*own).unionByName(last)

    def checkpoint(self) -> int:
        """Fold the log up to now into a snapshot, dealt by row id; later reads start from it."""
        version = self.db.version
        path = f"{self.db.root}/data/{self.name}/snapshot-{version}-{uuid.uuid4().hex}"
        rows = self.snapshot(with_id=True)
        made = rows.select(
            *(F.col(f"`{c}`") for c in self.columns), F.lit("INSERT").alias("_action"), "_row_id", F.lit(None).cast(self.schema).alias("_before"),
            F.lit(None).cast("timestamp_ntz").alias("_time"), F.lit(0).cast("long").alias("_commit_no"), F.lit(0).cast("long").alias("_seq"),
        )
        made.write.parquet(path)
        self.meta.snapshots[str(version)] = path
        self.db.save()
        return version

    def set_insert_only(self, on: bool) -> None:
        """Before the declaration the history may hold updates and deletes; readers test the slice they read."""
        if not on:
            self.db.require_no_cursor(self.name)
        self.meta.insert_only = on
        self.db.save()

    def add_increasing(self, c: Increasing, enabled: bool = True, validate: bool = False) -> None:
        """ENABLE seeds the maximum from the data; RELY or DISABLE take it as told. VALIDATE is refused: the order in
        which the rows there are came is not kept in their values."""
        if validate:
            raise StandingQueryError("rows that are there cannot be validated")
        state = c.state()
        if enabled and not c.rely:
            top = self.snapshot().agg(F.max(F.col(f"`{c.column}`"))).first()[0]
            Increasing.advance(state, top)
        state["enabled"] = enabled
        self.meta.increasing[c.column] = state
        self.db.save()

    def alter_grace(self, column: str, grace: Any) -> list[str]:
        """A larger grace is only noted; a smaller one makes open cursors start again, whose names are returned."""
        state = self.meta.increasing[column]
        old = Increasing.grace_of(state)
        state["grace"] = Increasing.pack(grace)
        self.db.save()
        return [] if old is None or grace >= old else [c for c, tables in self.db.cursors.items() if self.name in tables]

    def set_finalize(self, predicate: str | None) -> None:
        """Attach or move a finalization predicate. Rows final before must be final after."""
        from standq.plans.prover import require_monotone

        if predicate is not None:
            require_monotone(predicate)
            if self.meta.finalize:
                back = self.snapshot().filter(F.expr(self.meta.finalize) & ~F.coalesce(F.expr(predicate), F.lit(False))).limit(1)
                if not back.isEmpty():
                    raise ConstraintViolation("final rows would become open again")
        self.meta.finalize = predicate
        self.db.save()

    def drop_partition(self, where: str) -> int:
        with self.db.transaction() as tx:
            tx.delete(self.name, where)
        return self.db.version

    def exchange_partition(self, where: str, rows: DataFrame) -> int:
        with self.db.transaction() as tx:
            tx.delete(self.name, where)
            tx.insert(self.name, rows)
        return self.db.version

    def add_partition(self, rows: DataFrame) -> int:
        with self.db.transaction() as tx:
            tx.insert(self.name, rows)
        return self.db.version


class Transaction:
    """Statements see committed rows and this transaction's own. Each stages Parquet files; the manifest makes them count."""

    def __init__(self, db: Database):
        self.db, self.number = db, db.refresh() + 1
        self.entries: dict[str, dict[str, Any]] = {}
        self.bookmarks: dict[str, int] = {}
        self.deferred: list[Callable[[], None]] = []
        self.seq = 0
        self.staged: list[str] = []
        self.done = False
        self.started = {n: {c: dict(s) for c, s in m.increasing.items()} for n, m in db.metas.items()}

    def _entry(self, name: str) -> dict[str, Any]:
        return self.entries.setdefault(name, {"files": [], "inserts": 0, "updates": 0, "deletes": 0, "stats": {}})

    def snapshot(self, name: str, with_id: bool = False) -> DataFrame:
        return self.db.table(name).snapshot(self.number - 1, self.entries.get(name, {}).get("files"), with_id)

    def _drop(self, path: str) -> None:
        self.staged.remove(path)
        self.db.log.delete(path.removeprefix(self.db.root + "/"))

    def abort(self) -> None:
        """Delete what was staged."""
        for path in list(self.staged):
            self._drop(path)

    def _stage(self, name: str, changes: DataFrame, kind: str, fresh: bool = False) -> int:
        """Write change records; counts and extremes of times and constrained columns come from the same job. ``fresh``:
        inserts alone, with row ids that no other record has. A statement without rows leaves nothing."""
        table = self.db.table(name)
        meta, entry = table.meta, self._entry(name)
        self.seq += 1
        path = f"{self.db.root}/data/{name}/{'ins-' if fresh else ''}{uuid.uuid4().hex}"
        self.staged.append(path)
        tracked, noted = [c for c, s in meta.increasing.items() if s["enabled"]], table.noted()
        made = changes.withColumn("_time", F.lit(self.db.clock.now()).cast("timestamp_ntz")).withColumn("_commit_no", F.lit(self.number).cast("long"))
        made = made.withColumn("_seq", F.lit(self.seq).cast("long")).select(*(F.col(f"`{c}`") for c in log_schema(table.schema).fieldNames()))
        touched = F.col("_action") == "DELETE"
        # counts and extremes come from the job that writes; extremes as text, which keeps every digit
        measures = [F.count(F.lit(1)).alias("n")]
        for c in noted:
            new, low = F.when(~touched, F.col(f"`{c}`")), F.least(F.col(f"`{c}`"), F.col("_before")[c])
            measures += [F.min(low).cast("string").alias(f"min_{c}"), F.max(new).cast("string").alias(f"max_{c}"), F.sum(F.col(f"`{c}`").isNull().cast("long")).alias(f"null_{c}")]
        for k, check in enumerate(meta.checks):
            measures.append(F.sum((~touched & (~F.expr(check))).cast("long")).alias(f"check_{k}"))
        if meta.finalize:
            final = F.expr(meta.finalize)
            own = F.coalesce(final, F.lit(False))
            measures.append(F.sum(own.cast("long")).alias("final_new"))
        observed = Observation()
        made.observe(observed, *measures).write.parquet(path)
        seen = observed.get
        if not seen.get("n"):
            self._drop(path)
            return 0
        value = lambda kind, c: None if seen[f"{kind}_{c}"] is None else parse_value(seen[f"{kind}_{c}"], table.schema[c].dataType.simpleString())
        written = self.db.spark.read.schema(log_schema(table.schema)).parquet(path)
        if meta.finalize and kind != "INSERT":
            before = written.select("_before.*").filter(F.expr(meta.finalize)).limit(1)
            if not before.isEmpty():
                raise ConstraintViolation(f"{name}: {kind} touches final rows")
        if meta.finalize and seen["final_new"] and kind != "DELETE":
            raise ConstraintViolation(f"{name}: {kind} makes rows that are already final")
        for k, check in enumerate(meta.checks):
            if seen[f"check_{k}"]:
                raise ConstraintViolation(f"{name}: {seen[f'check_{k}']} rows violate {check}")
        for c in tracked:
            state = meta.increasing[c]
            if seen[f"null_{c}"] and not state.get("nulls_ok"):
                raise ConstraintViolation(f"{name}: null in increasing column {c}")
            if state.get("by"):
                self._check_by(name, c, state, written)
                continue
            # a row of this transaction may change again: the maximum is that at its start
            start = self.started[name][c]
            test = lambda least=value("min", c), start=start, c=c: check_increasing(start, least, c)
            if state.get("timing") == "deferred":
                self.deferred.append(test)
            else:
                test()
        for c in noted:
            if (top := value("max", c)) is not None:
                low, at = value("min", c), entry["stats"].get(c)
                like = table.schema[c].dataType.simpleString()
                low, top = (low, top) if at is None else (min(low, parse_value(at[0], like)), max(top, parse_value(at[1], like)))
                entry["stats"][c] = [str(low), str(top)]
        entry["files"].append(path)
        entry[{"INSERT": "inserts", "UPDATE": "updates", "DELETE": "deletes"}[kind]] += seen["n"]
        return seen["n"]

    def _check_by(self, name: str, c: str, state: dict[str, Any], written: DataFrame) -> None:
        held = self.db.table(name).snapshot(self.number - 1)
        new = written.filter("_action <> 'DELETE'")
        test = lambda: check_increasing_by(state, new, held, c)
        if state.get("timing") == "deferred":
            self.deferred.append(test)
        else:
            test()

    def insert(self, name: str, rows: DataFrame, late: Late | None = None) -> int:
        """Returns the number of rows kept; ``late`` says what becomes of rows too far behind."""
        table = self.db.table(name)
        own = rows.select(*(F.col(f"`{c}`") for c in table.columns))
        if late:
            own = late.split(self, table, own)
        made = own.select(
            "*", F.lit("INSERT").alias("_action"), row_ids(F.lit(self.number), F.lit(self.seq + 1)).alias("_row_id"),
            F.lit(None).cast(table.schema).alias("_before"),
        )
        return self._stage(name, made, "INSERT", fresh=True)

    def _forbid(self, name: str, what: str) -> None:
        if self.db.metas[name].insert_only:
            raise ConstraintViolation(f"{name} is insert-only: no {what}")

    def update(self, name: str, set_: dict[str, str | Column], where: str | Column | None = None) -> int:
        self._forbid(name, "update")
        table = self.db.table(name)
        rows = self.snapshot(name, True).filter(F.expr(where) if isinstance(where, str) else where if where is not None else F.lit(True))
        new = {c: F.expr(v) if isinstance(v, str) else v for c, v in set_.items()}
        before = F.struct(*(F.col(f"`{c}`") for c in table.columns))
        made = rows.select(
            *((new[f.name].cast(f.dataType) if f.name in new else F.col(f"`{f.name}`")).alias(f.name) for f in table.schema.fields),
            F.lit("UPDATE").alias("_action"), "_row_id", before.alias("_before"),
        )
        return self._stage(name, made, "UPDATE")

    def delete(self, name: str, where: str | Column | None = None) -> int:
        self._forbid(name, "delete")
        table = self.db.table(name)
        rows = self.snapshot(name, True).filter(F.expr(where) if isinstance(where, str) else where if where is not None else F.lit(True))
        before = F.struct(*(F.col(f"`{c}`") for c in table.columns))
        return self._stage(name, rows.select(*(F.col(f"`{c}`") for c in table.columns), F.lit("DELETE").alias("_action"), "_row_id", before.alias("_before")), "DELETE")

    def apply(self, name: str, changes: DataFrame) -> int:
        """Stage ready-made change records (a task's net changes) as one statement of the kind that needs most checks."""
        if self.db.metas[name].insert_only:
            return self._stage(name, changes.filter("_action = 'INSERT'"), "INSERT")
        return self._stage(name, changes, "UPDATE")

    def commit(self) -> int | None:
        for test in self.deferred:
            test()
        if not self.entries and not self.bookmarks:
            return None
        if self.db.refresh() + 1 != self.number:
            raise ConcurrentCommit(f"commit {self.number} is taken")
        manifest = {"commit": self.number, "time": self.db.clock.now(), "tables": self.entries, "bookmarks": self.bookmarks}

        def visible() -> None:
            self.done = True

        self.db.publish(manifest, visible)
        return self.number

"""Worked traces, value by value."""

from __future__ import annotations

from datetime import date, datetime, timedelta

import pytest
from pyspark.sql import functions as F

from standq.errors import ConstraintViolation, Dependent, IllegalTransition, NotInsertOnly, NotMonotone, UnboundedState
from standq.operators.constraints import Increasing
from standq.operators.cursor import ContinuousCursor, SnapshotCursor, Subscription
from standq.operators.final import FinalWindow, check_invariants, state_bound
from standq.operators.task import Cron, ErrorPolicy, Every, OnCommit, OnDemand, Scheduler, Task, View, create_target, keep_in_sync
from standq.operators.windows import window_table
from standq.plans.relation import changes

SIZE, STEP, START = timedelta(days=5), timedelta(days=2), date(2019, 11, 15)


def key_values(db, spark):
    db.create_table("t", "key string, val int", ["key"])
    with db.transaction() as tx:
        for k, v in (("A", 1), ("B", 2), ("C", 3)):
            tx.insert("t", spark.createDataFrame([(k, v)], "key string, val int"))


def edit(db):
    with db.transaction() as tx:
        tx.update("t", {"val": "20"}, "key = 'B'")
        tx.delete("t", "key = 'C'")


def test_change_log(db, spark):
    db.create_table("t", "key string, val int", ["key"])
    assert changes(db.rel("t")).count() == 0
    db.drop_table("t")
    key_values(db, spark)
    assert sorted((r.key, r.val, r._action) for r in changes(db.rel("t")).collect()) == [("A", 1, "INSERT"), ("B", 2, "INSERT"), ("C", 3, "INSERT")]
    edit(db)
    second = changes(db.rel("t"), 1, 2, encoding="pair").collect()
    assert sorted((r.key, r.val, r._action) for r in second) == [("B", 2, "DELETE"), ("B", 20, "UPDATE"), ("C", 3, "DELETE")]
    ids = {r.key: r._row_id for r in changes(db.rel("t"), 0, 1).collect()}
    assert all(r._row_id == ids[r.key] for r in second)


def test_replication(db, spark):
    db.create_table("t", "key string, val int", ["key"])
    db.create_table("copy", "key string, val int")
    Task.apply_changes(db, "follow", db.rel("t"), "copy")
    db.metas.pop("t")
    key_values(db, spark)
    rows = lambda: sorted(map(tuple, db.table("copy").snapshot().collect()))
    assert rows() == [("A", 1), ("B", 2), ("C", 3)]
    edit(db)
    assert rows() == [("A", 1), ("B", 20)]


def test_window_members(sensor):
    rows = window_table(sensor().rel("sensor").to_df(), "day", SIZE, STEP, START)
    got = [(r.win_start.day, r["count"]) for r in rows.groupBy("win_start").count().orderBy("win_start").collect()]
    assert [n for _, n in got] == [5, 5, 4, 2, 2, 4, 4, 2]
    shown = window_table(sensor_rows(rows), "day", SIZE, STEP, START, bounds="inclusive").filter("win_start = date'2019-11-15'")
    assert shown.select("win_end").distinct().collect()[0][0] == date(2019, 11, 19)


def sensor_rows(rows):
    return rows.select("place", "day", "measure").distinct()


def test_verbose(sensor):
    db = sensor()
    query = db.rel("sensor").window("day", SIZE, STEP, START).aggregate(["place", "win_start", "win_end"], total="sum(measure)")
    made = changes(query, format="LOG", encoding="delete_insert").orderBy("_commit_no", "win_start", F.col("_action") == "INSERT").collect()
    signs = [(-1 if r._action == "DELETE" else 1, r.total, r._commit_no) for r in made]
    assert len(signs) == 48 and sum(s > 0 for s, _, _ in signs) == 28
    first = [(s, t) for s, t, c in signs if c <= 5 and True][:9]
    assert [t for s, t, c in signs if c == 4 and s > 0][0] == 123
    assert [t for s, t, c in signs if c == 5 and s > 0][0] == 157
    assert first[0] == (1, 30)
    assert [(s, t) for s, t, c in signs if c == 13][-2:] == [(-1, 34), (1, 68)]


@pytest.mark.parametrize(("grace", "sums"), [(None, [157, 158, 132, 68, 69, 136]), (timedelta(days=1), [157, 158, 132, 68, 69])])
def test_final(sensor, grace, sums):
    db = sensor(grace)
    rel = FinalWindow(db.rel("sensor"), "day", ["place"], {"total": ("sum", "measure")}, SIZE, STEP, START)
    assert [r.total for r in rel.to_df().orderBy("win_start").collect()] == sums
    cursor, got = ContinuousCursor(rel, rules="extended"), []
    for _ in range(db.version):
        got += [(r.win_start, r.total) for r in cursor.fetch(max_commits=1).df.collect()]
    assert [t for _, t in sorted(got)] == sums
    assert check_invariants(db.table("sensor"), "day", []) == {"below_frontier": 0, "given_twice": 0}
    assert state_bound(SIZE, STEP, grace) >= 3


def test_final_literal_closure(sensor):
    rel = FinalWindow(sensor().rel("sensor"), "day", ["place"], {"total": ("sum", "measure")}, SIZE, STEP, START, closure="literal")
    assert [r.total for r in rel.to_df().orderBy("win_start").collect()] == [157, 158, 132, 68, 69]


@pytest.mark.parametrize(("grace", "ok"), [(30, True), (10, False)])
def test_bids(db, spark, grace, ok):
    db.create_table("bids", "at timestamp_ntz, price int", insert_only=True, increasing=[Increasing("at", grace=timedelta(seconds=grace))])
    bid = lambda s: spark.createDataFrame([(datetime(2024, 1, 1, 14, 55, s), 1)], "at timestamp_ntz, price int")
    for s in (0, 10, 20, 30):
        with db.transaction() as tx:
            tx.insert("bids", bid(s))
    if ok:
        with db.transaction() as tx:
            tx.insert("bids", bid(5))
    else:
        with pytest.raises(ConstraintViolation), db.transaction() as tx:
            tx.insert("bids", bid(5))
    assert db.table("bids").snapshot().count() == 4 + ok


def test_strict_and_deferred(db, spark):
    db.create_table("s", "n int", insert_only=True, increasing=[Increasing("n", strict=True, timing="deferred")])
    rows = lambda *v: spark.createDataFrame([(x,) for x in v], "n int")
    with db.transaction() as tx:
        tx.insert("s", rows(3, 1, 2))
    with pytest.raises(ConstraintViolation), db.transaction() as tx:
        tx.insert("s", rows(3))
    with pytest.raises(ConstraintViolation), db.transaction() as tx:
        tx.insert("s", rows(None))
    with db.transaction() as tx:
        tx.insert("s", rows(4))
    assert db.table("s").snapshot().count() == 4


def stream(db, spark, n=1):
    db.create_table("ev", "id int, v int", ["id"], True)
    return lambda *ids: insert(db, spark, ids)


def insert(db, spark, ids):
    with db.transaction() as tx:
        tx.insert("ev", spark.createDataFrame([(i, i * 10) for i in ids], "id int, v int"))


def test_states(db, spark):
    add = stream(db, spark)
    db.create_table("copy", "id int, v int", insert_only=True)
    task = Task.insert(db, "c", db.rel("ev"), "copy")
    ids = lambda: sorted(r.id for r in db.table("copy").snapshot().collect())
    add(1)
    assert ids() == [1]
    assert task.alter("pause") == "PAUSED"
    add(2)
    assert ids() == [1]
    again = Task.insert(db, "c", db.rel("ev"), "copy")  # after a restart
    Scheduler.of(db).remove(task)
    assert again.state == "PAUSED"
    again.alter("resume")
    add(3)
    assert ids() == [1, 2, 3]
    again.alter("stop")
    with pytest.raises(IllegalTransition):
        again.alter("pause")
    add(4)
    again.alter("resume")
    add(5)
    assert ids() == [1, 2, 3, 5]
    again.drop()
    add(6)
    assert ids() == [1, 2, 3, 5]


def test_exactly_once_after_a_crash(db, spark):
    """A run that dies before its manifest leaves no rows and no bookmark behind."""
    from standq.sources.store import Transaction

    add = stream(db, spark)
    db.create_table("copy", "id int, v int", insert_only=True)
    task = Task.insert(db, "c", db.rel("ev"), "copy", schedule=OnDemand())
    add(1, 2)
    tx = Transaction(db)
    tx.apply("copy", task._changes(0, db.version))  # staged, never committed
    assert db.table("copy").snapshot().count() == 0
    assert task.run_now() is not None
    assert task.run_now() is None
    assert db.table("copy").snapshot().count() == 2


def test_schedules(db, spark):
    add = stream(db, spark)
    for n in ("sync", "async", "every", "demand", "cron", "both", "twice"):
        db.create_table(n, "id int, v int", insert_only=True)
    tasks = {
        "sync": OnCommit(), "async": OnCommit(asynchronous=True), "every": Every(seconds=60), "demand": OnDemand(), "cron": Cron(text="*/5 * * * *"),
        "both": Every(seconds=3600) | OnCommit(tables=("ev",)), "twice": OnCommit().times(2),
    }
    made = {n: Task.insert(db, f"t_{n}", db.rel("ev"), n, schedule=s) for n, s in tasks.items()}
    size = lambda: {n: db.table(n).snapshot().count() for n in tasks}
    add(1)
    assert size() == {"sync": 1, "async": 0, "every": 0, "demand": 0, "cron": 0, "both": 1, "twice": 1}
    Scheduler.of(db).tick()
    assert size()["async"] == 1
    db.clock.advance(seconds=61)
    Scheduler.of(db).tick()
    assert size()["every"] == 1 and size()["cron"] == 0
    db.clock.advance(minutes=5)
    Scheduler.of(db).tick()
    assert size()["cron"] == 1
    made["demand"].run_now()
    assert size()["demand"] == 1
    add(2)
    add(3)
    assert size()["twice"] == 2 and size()["sync"] == 3


def test_errors(db, spark):
    from standq.errors import RejectLimit

    add = stream(db, spark)
    db.create_table("copy", "id int, v int", insert_only=True, checks=["v < 50"])
    db.create_table("bad", "tag string, reason string, row_json string", insert_only=True)
    task = Task.insert(db, "c", db.rel("ev"), "copy", schedule=OnDemand(), errors=ErrorPolicy("bad", "x", 1, 2))
    add(1, 2, 9)
    task.run_now()
    assert db.table("copy").snapshot().count() == 2 and db.table("bad").snapshot().first().tag == "x"
    before = task.bookmark
    add(7, 8)
    with pytest.raises(RejectLimit):
        task.run_now()
    assert task.bookmark == before and db.table("copy").snapshot().count() == 2


def test_cursors(db, spark):
    add = stream(db, spark)
    add(1, 2)
    c = ContinuousCursor(db.rel("ev"), "c", yet_status=True)
    assert c.fetch().df.count() == 2
    assert c.fetch().status == "NO_DATA_YET"
    add(3)
    add(4)
    assert sorted(r.id for r in c.fetch(max_commits=1).df.collect()) == [3]
    c.commit()
    again = ContinuousCursor(db.rel("ev"), "c")
    assert sorted(r.id for r in again.fetch().df.collect()) == [4]
    with pytest.raises(Dependent):
        db.table("ev").set_insert_only(False)
    again.close()
    db.table("ev").set_insert_only(False)
    with pytest.raises(NotInsertOnly):
        ContinuousCursor(db.rel("ev"))
    ContinuousCursor(db.rel("ev").changes(), strict_syntax=True).close()
    with pytest.raises(NotInsertOnly):
        ContinuousCursor(db.rel("ev").aggregate([], n="count(*)"))


def test_snapshot_cursor(db, spark):
    add = stream(db, spark)
    add(1, 2, 3)
    c = SnapshotCursor(db.rel("ev"), ["id"])
    assert [r.id for r in c.next(2).collect()] == [1, 2]
    add(4)
    assert [r.id for r in c.last().collect()] == [3] and [r.id for r in c.prior().collect()] == [2] and [r.id for r in c.first().collect()] == [1]
    assert [r.id for r in SnapshotCursor(db.rel("ev"), ["id"], sensitive=True).last().collect()] == [4]


def test_subscription(db, spark):
    add, seen = stream(db, spark), []
    s = Subscription(db.rel("ev").where("v > 10"), lambda df: seen.extend(r.id for r in df.collect()))
    add(1, 2)
    add(3)
    s.cancel()
    add(4)
    assert sorted(seen) == [2, 3]


def test_insert_only(db, spark):
    add = stream(db, spark)
    add(1)
    for f in (lambda tx: tx.update("ev", {"v": "0"}), lambda tx: tx.delete("ev")):
        with pytest.raises(ConstraintViolation), db.transaction() as tx:
            f(tx)
    with pytest.raises(ConstraintViolation):
        db.table("ev").drop_partition("id = 1")
    assert db.table("ev").snapshot(0).exceptAll(db.table("ev").snapshot()).isEmpty()


def test_finalization(db, spark):
    db.create_table("ledger", "day date, amount int")
    rows = spark.createDataFrame([(date(2023, 10, 30), 1), (date(2023, 11, 2), 2)], "day date, amount int")
    with db.transaction() as tx:
        tx.insert("ledger", rows)
    t = db.table("ledger")
    t.set_finalize("day < date'2023-11-01'")
    for f in (
        lambda tx: tx.update("ledger", {"amount": "9"}, "day < date'2023-11-01'"), lambda tx: tx.delete("ledger", "amount = 1"),
        lambda tx: tx.insert("ledger", rows.filter("amount = 1")), lambda tx: tx.update("ledger", {"day": "date'2023-10-01'"}, "amount = 2"),
    ):
        with pytest.raises(ConstraintViolation), db.transaction() as tx:
            f(tx)
    with db.transaction() as tx:
        tx.update("ledger", {"amount": "5"}, "amount = 2")
    t.set_finalize("day < date'2023-12-01'")
    with pytest.raises(ConstraintViolation):
        t.set_finalize("day < date'2023-11-01'")
    with pytest.raises(NotMonotone):
        t.set_finalize("day > current_date()")


def test_unbounded_final(db, spark):
    stream(db, spark)
    with pytest.raises(UnboundedState):
        FinalWindow(db.rel("ev"), "v", [], {"n": ("count", "id")}, 10)


def test_own_writes_and_partitions(db, spark):
    db.create_table("t", "id int, v int", ["id"])
    with db.transaction() as tx:
        tx.insert("t", spark.createDataFrame([(1, 1), (2, 2)], "id int, v int"))
        tx.update("t", {"v": "v + 10"}, "id = 1")
        assert sorted(map(tuple, tx.snapshot("t").collect())) == [(1, 11), (2, 2)]
        assert db.table("t").snapshot().count() == 0
    db.table("t").exchange_partition("id = 2", spark.createDataFrame([(2, 7)], "id int, v int"))
    db.table("t").add_partition(spark.createDataFrame([(3, 3)], "id int, v int"))
    db.table("t").drop_partition("id = 1")
    assert sorted(map(tuple, db.table("t").snapshot().collect())) == [(2, 7), (3, 3)]
    version = db.table("t").checkpoint()
    with db.transaction() as tx:
        tx.delete("t", "id = 3")
    assert version < db.version and sorted(map(tuple, db.table("t").snapshot().collect())) == [(2, 7)]
    from standq.sources.store import Database

    assert sorted(map(tuple, Database(spark, db.root).table("t").snapshot().collect())) == [(2, 7)]


def test_rollback(db, spark):
    stream(db, spark)
    with pytest.raises(RuntimeError), db.transaction() as tx:
        tx.insert("ev", spark.createDataFrame([(1, 1)], "id int, v int"))
        raise RuntimeError
    assert db.version == 0 and db.table("ev").snapshot().count() == 0


def test_views_and_sync(db, spark):
    from standq.errors import StandingQueryError

    add = stream(db, spark)
    add(1)
    create_target(db, "auto", db.rel("ev"), True)
    assert keep_in_sync(db, "auto", db.rel("ev")).kind == "insert"
    add(2)
    assert db.table("auto").snapshot().count() == 2
    view = View(db, "ev", {"number": "id", "value": "v"}, "v > 0")
    with db.transaction() as tx:
        view.insert(tx, spark.createDataFrame([(3, 30)], "number int, value int"))
    with pytest.raises(StandingQueryError), db.transaction() as tx:
        view.insert(tx, spark.createDataFrame([(3, 0)], "number int, value int"))
    assert db.table("auto").snapshot().count() == 3


def test_merged_files(db, spark):
    from standq.sources.store import Database

    add = stream(db, spark)
    for i in range(4):
        add(i)
    assert db.table("ev").merge_files(0, 3) == 3
    assert len(db.table("ev").files(0, 4)) == 2
    for handle in (db, Database(spark, db.root)):
        assert [sorted(r.id for r in handle.table("ev").log_slice(v, v + 1).collect()) for v in range(4)] == [[0], [1], [2], [3]]
        assert handle.table("ev").snapshot(2).count() == 2 and handle.table("ev").snapshot().count() == 4


def test_chain_and_failing_task(db, spark):
    """A task that fails within a commit does not undo it, and the constraint still moves."""
    from standq.errors import RejectLimit

    db.create_table("n", "v int", insert_only=True, increasing=[Increasing("v")])
    db.create_table("copy", "v int", insert_only=True, checks=["v < 5"])
    Task.insert(db, "c", db.rel("n"), "copy")
    with pytest.raises(RejectLimit), db.transaction() as tx:
        tx.insert("n", spark.createDataFrame([(9,)], "v int"))
    assert db.table("n").snapshot().count() == 1 and Increasing.max_of(db.metas["n"].increasing["v"]) == 9


def test_increasing_by_key(db, spark):
    db.create_table("turns", "conv string, turn int", insert_only=True, increasing=[Increasing("turn", strict=True, by=("conv",))])
    rows = lambda *v: spark.createDataFrame(v, "conv string, turn int")
    for v in ((("a", 5), ("b", 1)), (("b", 2), ("c", 0))):
        with db.transaction() as tx:
            tx.insert("turns", rows(*v))
    with pytest.raises(ConstraintViolation), db.transaction() as tx:
        tx.insert("turns", rows(("b", 9), ("a", 5)))
    assert db.table("turns").snapshot().count() == 4

"""Cases that must not go wrong: several handles, orphan files, colliding identities, null keys, leases, threads."""

from __future__ import annotations

import time
from datetime import datetime, timedelta

import pytest
from pyspark.sql import functions as F

from standq import measures
from standq.clock import ManualClock, SystemClock
from standq.errors import ConcurrentCommit, ConstraintViolation, NotInsertOnly
from standq.operators.constraints import Increasing
from standq.operators.cursor import ContinuousCursor
from standq.operators.joins import as_of_join
from standq.operators.task import Every, Lease, OnCommit, Scheduler, Task, create_target
from standq.plans.relation import Join, SetOperation, Sql, changes, key_id, per_commit_changes
from standq.sources.store import Database


def put(db, name, rows, kinds):
    with db.transaction() as tx:
        tx.insert(name, db.spark.createDataFrame(rows, kinds))


def test_two_handles_share_catalog_and_maximum(db, spark):
    two = Database(spark, db.root, db.clock)
    db.create_table("t", "v int", increasing=[Increasing("v")])
    put(db, "t", [(100,)], "v int")
    with pytest.raises(ConstraintViolation):
        put(two, "t", [(5,)], "v int")
    assert two.table("t").snapshot().count() == 1
    two.table("t").set_insert_only(True)
    db.refresh()
    assert db.metas["t"].insert_only
    two.create_table("u", "v int")
    with pytest.raises(ConcurrentCommit):
        db.table("t").set_insert_only(False)  # made from a catalog that is older
    assert db.metas["t"].insert_only and "u" in db.metas


def test_a_table_made_again_begins_empty(db):
    db.create_table("t", "v int")
    put(db, "t", [(1,)], "v int")
    db.drop_table("t")
    db.create_table("t", "v int")
    assert db.table("t").snapshot().count() == 0
    put(db, "t", [(2,)], "v int")
    assert [r.v for r in db.table("t").snapshot().collect()] == [2]


def test_a_failed_transaction_leaves_no_files(db, spark):
    db.create_table("t", "v int", checks=["v > 0"])
    put(db, "t", [(1,)], "v int")
    files = lambda: {f for f in db.log.names("data/t")}
    before = files()
    with pytest.raises(ConstraintViolation):
        put(db, "t", [(-1,)], "v int")
    assert files() == before and db.version == 1


def test_rows_of_one_key_live_apart(db, spark):
    db.create_table("t", "k int, v int", ["k"])
    put(db, "t", [(1, 1), (1, 2), (2, 3), (None, 4), (None, 5)], "k int, v int")
    with db.transaction() as tx:
        tx.update("t", {"v": "v + 10"}, "k = 2")
        tx.delete("t", "v = 4")
    assert sorted(r.v for r in db.table("t").snapshot().collect()) == [1, 2, 5, 13]
    db.table("t").checkpoint()
    with db.transaction() as tx:
        tx.delete("t", "v = 2")
    assert sorted(r.v for r in db.table("t").snapshot().collect()) == [1, 5, 13]
    assert sorted(r.v for r in db.table("t").snapshot(1).collect()) == [1, 2, 3, 4, 5]


def test_identities_do_not_run_together(spark):
    rows = spark.createDataFrame([("a\x1fvb", "c"), ("a", "b\x1fvc"), ("n", None), (None, "n"), ("1:a", ""), ("", "1:a")], "x string, y string")
    assert rows.select(key_id(["x", "y"])).distinct().count() == 6


def test_cursor_from_before_the_declaration(db, spark):
    db.create_table("t", "k int")
    put(db, "t", [(1,), (2,)], "k int")
    with db.transaction() as tx:
        tx.delete("t", "k = 1")
    db.table("t").set_insert_only(True)
    put(db, "t", [(3,)], "k int")
    with pytest.raises(NotInsertOnly):
        ContinuousCursor(db.rel("t"), start_at=1).fetch()
    assert [r.k for r in ContinuousCursor(db.rel("t"), start_at=2).fetch().df.collect()] == [3]
    assert sorted((r.k, r._sign) for r in db.rel("t").delta(1, 3).collect()) == [(1, -1), (3, 1)]


def test_as_of_join_of_nulls_and_ties(spark):
    at = lambda m: datetime(2024, 1, 31, 23, m)
    left = spark.createDataFrame([(1, "a", at(10)), (2, None, at(10)), (3, "a", None), (4, "b", at(1)), (5, "a", at(59) + timedelta(minutes=5))], "id int, k string, ts timestamp_ntz")
    right = spark.createDataFrame([("a", at(5), 1), ("a", at(5), 3), ("a", at(5), 2), (None, at(1), 9), ("a", None, 9), ("b", at(2), 9)], "k string, ts timestamp_ntz, p int")
    got = {r.id: r.p for r in as_of_join(left, right, "ts", ["k"], ["p"]).collect()}
    assert got == {1: 3, 2: None, 3: None, 4: None, 5: 3}


def test_merge_refuses_two_rows_for_one(db, spark):
    db.create_table("s", "k int, v int", insert_only=True)
    db.create_table("t", "k int, v int")
    put(db, "t", [(1, 0)], "k int, v int")
    Task.merge(db, "m", db.rel("s"), "t", ["k"], {"v": "s_v"}, schedule=Every(seconds=1))
    put(db, "s", [(1, 1), (1, 2)], "k int, v int")
    db.clock.advance(seconds=5)
    with pytest.raises(ConstraintViolation):
        Scheduler.of(db).tick()
    assert [r.v for r in db.table("t").snapshot().collect()] == [0]


def test_views_of_the_user_come_back(db, spark):
    spark.range(7).createOrReplaceTempView("t")
    db.create_table("t", "k int")
    put(db, "t", [(1,)], "k int")
    rel = Sql(db, "SELECT k FROM t", ["t"])
    assert rel.to_df().count() == 1 and spark.table("t").count() == 7
    spark.catalog.dropTempView("t")
    assert rel.to_df().count() == 1 and not spark.catalog.tableExists("t")


@pytest.mark.parametrize("op", ["intersect all", "except all"])
def test_all_set_operations_follow(db, spark, op):
    for t in ("a", "b"):
        db.create_table(t, "s string")
    rel = SetOperation(db.rel("a"), db.rel("b"), op)
    put(db, "a", [("x",), ("x",), ("x",), ("y",), (None,), (None,)], "s string")
    put(db, "b", [("x",), ("y",), (None,)], "s string")
    with db.transaction() as tx:
        tx.delete("b", "s = 'y'")
    for v in range(3):
        a, b = rel.delta(v, v + 1), rel.difference(v, v + 1)
        assert sorted(map(str, a.collect())) == sorted(map(str, b.select(*a.columns).collect())), v
    want = ["None", "x"] if op == "intersect all" else ["None", "x", "x", "y"]
    assert sorted(str(r.s) for r in rel.to_df().collect()) == want


def test_theta_join_change_is_difference(db, spark):
    db.create_table("a", "x int")
    db.create_table("b", "y int")
    rel = Join(db.rel("a"), db.rel("b"), condition="y < x")
    put(db, "a", [(1,), (5,)], "x int")
    put(db, "b", [(0,), (3,)], "y int")
    with db.transaction() as tx:
        tx.update("a", {"x": "x - 3"}, "x = 5")
        tx.delete("b", "y = 0")
    for v in range(3):
        key = lambda df: sorted((r.x, r.y, r._sign) for r in df.select("x", "y", "_sign").groupBy("x", "y").agg(F.sum("_sign").alias("_sign")).filter("_sign <> 0").collect())
        assert key(rel.delta(v, v + 1)) == key(rel.difference(v, v + 1)), v
    with pytest.raises(ValueError):
        Join(db.rel("a"), db.rel("a"), condition="true")


def test_commits_in_one_plan_equal_commit_by_commit(db, spark):
    db.create_table("t", "g string, v decimal(10,2), ts timestamp_ntz", insert_only=True)
    data = [[("a", 1, 0), ("b", 2, 1)], [("a", 3, 2)], [("c", 0, 3), (None, 4, 4)], [("b", None, 5), ("a", -1, 6)]]
    for rows in data:
        with db.transaction() as tx:
            made = spark.createDataFrame([(g, v, datetime(2024, 1, 1, h)) for g, v, h in rows], "g string, v int, ts timestamp_ntz")
            tx.insert("t", made.withColumn("v", F.col("v").cast("decimal(10,2)")))
    rel = db.rel("t").window("ts", timedelta(hours=3), timedelta(hours=1), datetime(2024, 1, 1)).aggregate(["g"], s="sum(v)", n="count(*)", lo="min(v)", hi="cast(max(v) as double)")
    for start in (0, 2):
        one = per_commit_changes(rel, start, 4).select("g", "s", "n", "lo", "hi", "_action", "_before", "_commit_no")
        each = []
        for v in range(start, 4):
            each += changes(rel, v, v + 1, encoding="single").withColumn("_commit_no", F.lit(v + 1)).select(*one.columns).collect()
        assert sorted(map(str, (tuple(r) for r in one.collect()))) == sorted(map(str, (tuple(r) for r in each)))


def test_rows_read(db, spark):
    db.create_table("t", "k int", insert_only=True)
    put(db, "t", [(i,) for i in range(100)], "k int")
    put(db, "t", [(i,) for i in range(7)], "k int")
    got = measures.work_ratio(db.rel("t")).collect()
    assert [(r.commit_no, r.delta_rows, r.full_rows) for r in got] == [(1, 100, 100), (2, 7, 107)]


def test_leases_keep_runs_apart(db):
    a, b = Lease(db, "x", 60), Lease(db, "x", 60)
    assert a.take() and not b.take()
    a.free()
    assert b.take()
    db.clock.advance(seconds=61)
    assert a.take()  # the other's lapsed
    b.free()
    assert not Lease(db, "x").take()  # a lapsed run does not free another's


def test_a_thread_runs_what_is_due(spark):
    from standq.scratch import scratch

    root = scratch(spark)
    db, other = Database(spark, root, SystemClock()), None
    db.create_table("s", "k int", insert_only=True)
    db.create_table("timed", "k int")
    db.create_table("later", "k int")
    Task.apply_changes(db, "t1", db.rel("s"), "timed", schedule=Every(seconds=0.2))
    Task.apply_changes(db, "t2", db.rel("s"), "later", schedule=OnCommit(asynchronous=True))
    scheduler = Scheduler.of(db)
    scheduler.start(0.2)
    try:
        other = Database(spark, root, SystemClock())
        put(other, "s", [(1,), (2,)], "k int")  # of another session
        for _ in range(150):
            other.refresh()
            if {"timed", "later"} <= {t for m in other.manifests for t in m["tables"]}:
                break
            time.sleep(0.2)
    finally:
        scheduler.stop()
    other.refresh()
    assert other.table("timed").snapshot().count() == 2 and other.table("later").snapshot().count() == 2
    assert all(name == "ConcurrentCommit" for name, _ in scheduler.failed)


def test_cursor_bounds(db, spark):
    db.create_table("t", "k int", insert_only=True)
    for n in (3, 4, 5):
        put(db, "t", [(i,) for i in range(n)], "k int")
        db.clock.advance(minutes=10)
    c = ContinuousCursor(db.rel("t"))
    assert [c.fetch(max_rows=7).df.count(), c.fetch(max_rows=1).df.count(), c.fetch(max_rows=1).status] == [7, 5, "NO_DATA"]
    start = ManualClock(datetime(2024, 1, 1, 12)).now()
    assert ContinuousCursor(db.rel("t"), start_at=start + timedelta(minutes=5)).fetch().df.count() == 9
    assert ContinuousCursor(db.rel("t"), start_at=start - timedelta(minutes=5)).fetch().df.count() == 12


def test_top_is_kept_between_commits(db, spark):
    db.create_table("t", "k int, v int")
    rel = db.rel("t").top(2, [("v", True), ("k", False)])
    create_target(db, "target", rel)
    Task.apply_changes(db, "follow", rel, "target")
    put(db, "t", [(1, 5), (2, 9), (3, 1)], "k int, v int")
    put(db, "t", [(4, 7)], "k int, v int")
    with db.transaction() as tx:
        tx.delete("t", "k = 2")
    with db.transaction() as tx:
        tx.update("t", {"v": "100"}, "k = 3")
    assert sorted((r.k, r.v) for r in db.table("target").snapshot().collect()) == [(3, 100), (4, 7)]

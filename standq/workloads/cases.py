"""Cases that a store, FINAL and the joins must get right: repeated keys, several handles, late declarations, late rows."""

from __future__ import annotations

from datetime import datetime, timedelta

from pyspark.sql import functions as F

from standq.errors import ConstraintViolation
from standq.operators.constraints import Increasing
from standq.operators.cursor import ContinuousCursor
from standq.operators.final import FinalWindow
from standq.operators.task import Task, create_target
from standq.plans.relation import Join, SetOperation
from standq.sources.store import Database
from standq.workloads.fixtures import EV_COMMIT, ev, fresh, read
from standq.workloads.flows import EV
from standq.workloads.registry import workload


@workload("duplicate_keys", "SELECT * FROM (VALUES (1, 'a'), (1, 'b'), (2, 'd'), (CAST(NULL AS INTEGER), 'e'), (NULL, 'f')) t(k, v)")
def duplicate_keys(spark, sf):
    """Rows of one key are rows of their own, whatever happens to other rows."""
    db = fresh(spark)
    db.create_table("t", "k int, v string", ["k"])
    with db.transaction() as tx:
        tx.insert("t", spark.createDataFrame([(1, "a"), (1, "b"), (2, "c"), (None, "e"), (None, "f")], "k int, v string"))
    with db.transaction() as tx:
        tx.update("t", {"v": "'d'"}, "k = 2")
    return db.table("t").snapshot()


@workload("two_writers", f"SELECT c, CASE WHEN c = 1 THEN 'rejected' ELSE 'accepted' END AS outcome, CASE WHEN c = 1 THEN 0 ELSE count(*) END AS held FROM {EV} WHERE c <= 3 GROUP BY c")
def two_writers(spark, sf):
    """An increasing maximum is the same for all handles of a database: after the second five days from one handle, those
    before come too late from another, and those after do not."""
    one, rows = fresh(spark), read(spark, sf, "events").withColumn("c", F.expr(EV_COMMIT).cast("long"))
    one.create_table("t", rows.schema, increasing=[Increasing("ts")])
    two, out = Database(spark, one.root, one.clock), []
    for db, c in ((one, 2), (two, 1), (two, 3)):
        try:
            with db.transaction() as tx:
                tx.insert("t", rows.filter(F.col("c") == c))
            out.append((c, "accepted"))
        except ConstraintViolation:
            out.append((c, "rejected"))
    held = two.table("t").snapshot().groupBy("c").agg(F.count("*").alias("held"))
    return spark.createDataFrame(out, "c long, outcome string").join(held, "c", "left").withColumn("held", F.coalesce("held", F.lit(0)))


@workload("insert_only_later", "SELECT * FROM (VALUES (1, 'b', -1), (1, 'c', 1), (2, 'x', -1), (3, 'n', 1)) t(k, v, sign)")
def insert_only_later(spark, sf):
    """Changes before the declaration are updates and deletes still."""
    db = fresh(spark)
    db.create_table("t", "k int, v string", ["k"])
    with db.transaction() as tx:
        tx.insert("t", spark.createDataFrame([(1, "b"), (2, "x")], "k int, v string"))
    with db.transaction() as tx:
        tx.update("t", {"v": "'c'"}, "k = 1")
        tx.delete("t", "k = 2")
    db.table("t").set_insert_only(True)
    with db.transaction() as tx:
        tx.insert("t", spark.createDataFrame([(3, "n")], "k int, v string"))
    return db.rel("t").delta(1, 3).select("k", "v", F.col("_sign").cast("int").alias("sign"))


LATE_ROWS = [(1, 0, 1.0), (2, 9, 2.0), (3, 3, 4.0), (4, 14, 8.0), (5, 21, 16.0)]


def late_flow(spark, **options):
    db = fresh(spark)
    db.create_table("t", "id int, ts timestamp_ntz, x double", insert_only=True, **options)
    for i, minute, x in LATE_ROWS:
        with db.transaction() as tx:
            tx.insert("t", spark.createDataFrame([(i, datetime(2024, 1, 1, 0, minute), x)], "id int, ts timestamp_ntz, x double"))
    return db


def late_windows(db, grace):
    rel = FinalWindow(db.rel("t"), "ts", [], {"total": ("sum", "x")}, timedelta(minutes=5), None, datetime(2024, 1, 1), grace)
    whole = rel.to_df().select(F.minute("win_start").alias("m"), "total", F.lit("at").alias("way"))
    for v in range(db.version):
        whole = whole.unionByName(rel.delta(v, v + 1).select(F.minute("win_start").alias("m"), "total", F.lit("delta").alias("way")))
    return whole


# grace 2 minutes: the row of minute 9 closes [0, 5), so that of minute 3 comes too late for it; minute 14 closes [5, 10), 21 [10, 15)
LATE = "SELECT * FROM (VALUES (0, 1.0, 'at'), (5, 2.0, 'at'), (10, 8.0, 'at'), (0, 1.0, 'delta'), (5, 2.0, 'delta'), (10, 8.0, 'delta')) t(m, total, way)"


@workload("final_no_constraint", LATE.replace("1.0", "CAST(1.0 AS DOUBLE)"))
def final_no_constraint(spark, sf):
    """FINAL of a column without a constraint, by the grace in the clause alone."""
    return late_windows(late_flow(spark), timedelta(minutes=2))


@workload("final_smaller_grace", LATE.replace("1.0", "CAST(1.0 AS DOUBLE)"))
def final_smaller_grace(spark, sf):
    """The clause's grace is less than the column's: what was closed stays as it was."""
    return late_windows(late_flow(spark, increasing=[Increasing("ts", grace=timedelta(minutes=10))]), timedelta(minutes=2))


@workload("theta_join_changes", "SELECT a.r_regionkey AS r, b.n_nationkey AS n, 1 AS sign FROM region a JOIN nation b ON b.n_regionkey < a.r_regionkey WHERE b.n_nationkey % 3 = 0")
def theta_join_changes(spark, sf):
    """The change of a join on any condition, derived when the second table gets its rows."""
    db = fresh(spark)
    for t in ("region", "nation"):
        db.create_table(t, read(spark, sf, t).schema, insert_only=True)
    with db.transaction() as tx:
        tx.insert("region", read(spark, sf, "region"))
        tx.insert("nation", read(spark, sf, "nation").filter("n_nationkey % 3 <> 0"))
    with db.transaction() as tx:
        tx.insert("nation", read(spark, sf, "nation").filter("n_nationkey % 3 = 0"))
    rel = Join(db.rel("region").select(r="r_regionkey"), db.rel("nation").select(n="n_nationkey", nr="n_regionkey"), condition="nr < r")
    return rel.delta(1, 2).select("r", "n", F.col("_sign").cast("int").alias("sign"))


def all_rows(spark, sf, op):
    db = fresh(spark)
    for t in ("a", "b"):
        db.create_table(t, "s string", insert_only=False)
    rel = SetOperation(db.rel("a"), db.rel("b"), op)
    create_target(db, "target", rel)
    Task.apply_changes(db, "follow", rel, "target")
    rows = read(spark, sf, "customer").select(F.col("c_mktsegment").alias("s"), "c_custkey")
    for t, where in (("a", "c_custkey % 2 = 0"), ("b", "c_custkey % 5 = 0"), ("a", "c_custkey % 2 = 1 AND c_custkey % 3 = 0")):
        with db.transaction() as tx:
            tx.insert(t, rows.filter(where).select("s"))
    return db.table("target").snapshot()


A_ROWS, B_ROWS = "SELECT c_mktsegment AS s FROM customer WHERE c_custkey % 2 = 0 OR c_custkey % 3 = 0", "SELECT c_mktsegment AS s FROM customer WHERE c_custkey % 5 = 0"


@workload("intersect_all_sync", f"{A_ROWS} INTERSECT ALL {B_ROWS}")
def intersect_all_sync(spark, sf):
    return all_rows(spark, sf, "intersect all")


@workload("except_all_sync", f"{A_ROWS} EXCEPT ALL {B_ROWS}")
def except_all_sync(spark, sf):
    return all_rows(spark, sf, "except all")


@workload("cursor_max_rows", f"SELECT count(*) AS n FROM {EV} WHERE c <= 2")
def cursor_max_rows(spark, sf):
    """Whole commits, as many as hold at most so many rows."""
    db = ev(spark, sf)
    sizes = [m["tables"]["ev"]["inserts"] for m in db.manifests]
    got = ContinuousCursor(db.rel("ev")).fetch(max_rows=sizes[0] + sizes[1] + sizes[2] // 2)
    return got.df.agg(F.count("*").alias("n"))


@workload("cursor_from_time", f"SELECT event_id, user_id, c FROM {EV} WHERE c > 1")
def cursor_from_time(spark, sf):
    """A cursor that begins after a moment."""
    db, rows = fresh(spark), read(spark, sf, "events").withColumn("c", F.expr(EV_COMMIT).cast("long"))
    db.create_table("t", rows.schema, insert_only=True)
    for c in range(1, 7):
        with db.transaction() as tx:
            tx.insert("t", rows.filter(F.col("c") == c))
        db.clock.advance(minutes=10)
    return ContinuousCursor(db.rel("t"), start_at=datetime(2024, 1, 1, 0, 5)).fetch().df.select("event_id", "user_id", "c")

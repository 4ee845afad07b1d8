"""Versioned tables made from the given ones by fixed rules, so that every state is also a SELECT."""

from __future__ import annotations

from collections.abc import Callable
from datetime import datetime, timedelta

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from standq.clock import ManualClock
from standq.operators.constraints import Increasing
from standq.scratch import scratch
from standq.sources.store import Database

START = datetime(2024, 1, 1)
_built: dict[tuple[str, str, str], Database] = {}


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def fresh(spark: SparkSession) -> Database:
    return Database(spark, scratch(spark), ManualClock(START))


def built(spark: SparkSession, sf_dir: str, name: str, make: Callable[[SparkSession, str], Database]) -> Database:
    """A database that queries only read is made once a session."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _built:
        _built[key] = make(spark, sf_dir)
    return _built[key]


EV_COMMIT = "1 + floor((day(ts) - 1) / 5)"


def make_ev(spark: SparkSession, sf_dir: str, grace: timedelta | None = None) -> Database:
    """``ev``: events, insert-only, in six commits."""
    db, rows = fresh(spark), read(spark, sf_dir, "events")
    db.create_table("ev", rows.schema, ["event_id"], True, [Increasing("ts", grace=grace)])
    db.ingest_history("ev", rows, F.expr(EV_COMMIT))
    return db


def ev(spark: SparkSession, sf_dir: str) -> Database:
    return built(spark, sf_dir, "ev", make_ev)


def ev_grace(spark: SparkSession, sf_dir: str) -> Database:
    return built(spark, sf_dir, "ev_grace", lambda s, d: make_ev(s, d, timedelta(days=1)))


def ev_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with an arrival: up to half an hour late, every 97th two days."""
    late = (F.col("event_id") * 7919) % 1800 + F.when(F.col("event_id") % 97 == 0, 172_800).otherwise(0)
    return read(spark, sf_dir, "events").withColumn("arrival", (F.col("ts").cast("timestamp").cast("double") * 1e6).cast("long") + late * 1_000_000)


Step = Callable[[Database], None]


def cust_steps(spark: SparkSession, sf_dir: str) -> list[Step]:
    """Five commits on ``cust``: load; raise some; delete some; bring some back; raise again, with transient keys."""
    base = read(spark, sf_dir, "customer")

    def c1(db):
        with db.transaction() as tx:
            tx.insert("cust", base)

    def c2(db):
        with db.transaction() as tx:
            tx.update("cust", {"c_acctbal": "round(c_acctbal + 100, 2)", "c_mktsegment": "'BUILDING'"}, "c_custkey % 7 = 0")

    def c3(db):
        with db.transaction() as tx:
            tx.delete("cust", "c_custkey % 11 = 0")

    def c4(db):
        with db.transaction() as tx:
            tx.insert("cust", base.filter("c_custkey % 22 = 0"))

    def c5(db):
        with db.transaction() as tx:
            tx.update("cust", {"c_acctbal": "round(c_acctbal + 50, 2)"}, "c_custkey % 7 = 0")
            tx.insert("cust", base.filter("c_custkey % 50 = 0").withColumn("c_custkey", F.col("c_custkey") + 1_000_000_000))
            tx.delete("cust", "c_custkey >= 1000000000")

    return [c1, c2, c3, c4, c5]


#: The state of ``cust`` after its last commit.
CUST_FINAL = """
  SELECT c_custkey, c_name, c_nationkey,
         CASE WHEN c_custkey % 22 = 0 THEN round(c_acctbal + CASE WHEN c_custkey % 7 = 0 THEN 50 ELSE 0 END, 2)
              WHEN c_custkey % 7 = 0 THEN round(round(c_acctbal + 100, 2) + 50, 2) ELSE c_acctbal END AS c_acctbal,
         CASE WHEN c_custkey % 7 = 0 AND c_custkey % 22 <> 0 THEN 'BUILDING' ELSE c_mktsegment END AS c_mktsegment
  FROM customer WHERE c_custkey % 11 <> 0 OR c_custkey % 22 = 0
"""


def ord_steps(spark: SparkSession, sf_dir: str) -> list[Step]:
    base = read(spark, sf_dir, "orders")

    def ins(where):
        def step(db):
            with db.transaction() as tx:
                tx.insert("ord", base.filter(where))

        return step

    def c3(db):
        with db.transaction() as tx:
            tx.update("ord", {"o_orderstatus": "'F'"}, "o_orderkey % 13 = 0 AND o_orderstatus = 'P'")

    def c4(db):
        with db.transaction() as tx:
            tx.delete("ord", "o_orderkey % 17 = 0")

    return [ins("o_orderkey % 10 < 7"), ins("o_orderkey % 10 IN (7, 8)"), c3, c4, ins("o_orderkey % 10 = 9")]


ORD_FINAL = """
  SELECT o_orderkey, o_custkey,
         CASE WHEN o_orderstatus = 'P' AND o_orderkey % 13 = 0 AND o_orderkey % 10 <> 9 THEN 'F' ELSE o_orderstatus END AS o_orderstatus,
         o_totalprice, o_orderdate, o_orderpriority
  FROM orders WHERE o_orderkey % 17 <> 0 OR o_orderkey % 10 = 9
"""


def play(db: Database, *columns: list[Step]) -> Database:
    for steps in columns:
        for step in steps:
            step(db)
            db.clock.advance(minutes=1)
    return db


def interleave(*columns: list[Step]) -> list[Step]:
    return [s for row in zip(*columns, strict=True) for s in row]


def cust_tables(spark: SparkSession, sf_dir: str, orders: bool = False) -> Database:
    db = fresh(spark)
    db.create_table("cust", read(spark, sf_dir, "customer").schema, ["c_custkey"])
    if orders:
        db.create_table("ord", read(spark, sf_dir, "orders").schema, ["o_orderkey"])
    return db


def cust(spark: SparkSession, sf_dir: str) -> Database:
    return built(spark, sf_dir, "cust", lambda s, d: play(cust_tables(s, d), cust_steps(s, d)))


def cust_ord(spark: SparkSession, sf_dir: str) -> Database:
    return built(spark, sf_dir, "cust_ord", lambda s, d: play(cust_tables(s, d, True), interleave(ord_steps(s, d), cust_steps(s, d))))

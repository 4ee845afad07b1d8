"""Prover, expiry, statements, streams, sources, joins, and the registered workloads."""

from __future__ import annotations

import math
from datetime import datetime, timedelta
from fractions import Fraction

import duckdb
import pytest
from pyspark.sql import functions as F

from standq.errors import ConcurrentCommit, ExpiredData, NotMonotone, StandingQueryError
from standq.functions.ranges import Months
from standq.operators import final
from standq.operators.expire import compare_policies, final_live, live, purge, row_state, set_policy
from standq.operators.final import Watermark, bucket_upper_bound
from standq.operators.windows import hop_aggregate, window_table
from standq.plans.prover import monotone_text, prove_insert_only
from standq.plans.relation import changes
from standq.plans.sql import Session
from standq.workloads import oracles, queries

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize(
    ("text", "ok"),
    [
        ("ts <= now()", True), ("ts >= now()", False), ("NOT (ts > now())", True), ("a = 1 AND ts < now() - INTERVAL '1' DAY OR b > 2", True), ("rand() < 0.5", False),
        ("date_trunc('day', now()) > ts", True), ("ts - now() < INTERVAL '1' DAY", True), ("now() - ts < INTERVAL '1' DAY", False), ("now() = ts", False),
    ],
)
def test_monotone(spark, text, ok):
    assert monotone_text(text) is ok


@pytest.mark.parametrize(
    ("query", "paper", "extended"),
    [
        ("WITH q AS (SELECT * FROM t) SELECT * FROM q", True, True), ("SELECT a FROM t INTERSECT SELECT b FROM t", True, True), ("SELECT a FROM t UNION SELECT b FROM t", True, True),
        ("VALUES (1)", True, True), ("SELECT x.a FROM t x JOIN t y ON x.a = y.b", True, True), ("SELECT * FROM t NATURAL JOIN (SELECT a FROM t)", True, True), ("SELECT x.a FROM t x CROSS JOIN t y", True, True),
        ("SELECT DISTINCT a FROM t", False, True), ("SELECT a FROM t GROUP BY a", False, True), ("SELECT a FROM t x LEFT SEMI JOIN t y ON x.a = y.b", False, True),
        ("SELECT count(*) FROM t", False, False), ("SELECT a FROM t EXCEPT SELECT b FROM t", False, False), ("SELECT x.a FROM t x LEFT JOIN t y ON x.a = y.b", False, False), ("SELECT a FROM t LIMIT 1", False, False),
        ("SELECT uuid() FROM t", False, False), ("SELECT a FROM u", False, False), ("SELECT a FROM t WHERE ts > now()", False, False), ("SELECT rank() OVER (ORDER BY a) FROM t", False, False),
        ("SELECT a FROM t WHERE a NOT IN (SELECT b FROM t)", False, False), ("SELECT a FROM t WHERE ts <= (SELECT max(ts) FROM t)", True, True), ("SELECT a FROM t WHERE ts < (SELECT max(ts) FROM u)", False, False),
    ],
)
def test_prover(spark, query, paper, extended):
    for n in ("t", "u"):
        spark.range(1).selectExpr("id a", "id b", "now() ts").createOrReplaceTempView(n)
    tables = {"t": True, "u": False}
    assert prove_insert_only(spark, query, tables).ok is paper
    assert prove_insert_only(spark, query, tables, "extended").ok is extended


NOW = datetime(2024, 2, 10)


def logs(db, spark):
    db.create_table("logs", "level string, ts timestamp_ntz", insert_only=True)
    rows = [("DEBUG", NOW - timedelta(hours=h)) for h in (1, 30)] + [("WARN", NOW - timedelta(days=d)) for d in (1, 8)]
    for r in rows:
        with db.transaction() as tx:
            tx.insert("logs", spark.createDataFrame([r], "level string, ts timestamp_ntz"))
    return db.table("logs")


def test_expiration(db, spark):
    t = logs(db, spark)
    old, new = "level = 'DEBUG' and ts < now() - interval '1' day", "level = 'DEBUG' and ts < now() - interval '1' day or level = 'WARN' and ts < now() - interval '7' day"
    set_policy(t, old)
    with pytest.raises(StandingQueryError):
        set_policy(t, old)
    with pytest.raises(NotMonotone):
        set_policy(t, "ts > now()", "modify")
    assert live(t, NOW).count() == 3
    assert compare_policies(t, old, new, NOW) == {"only_old": 0, "only_new": 1, "kind": "widens", "warn_purged": False}
    set_policy(t, new, "modify")
    assert live(t, NOW).count() == 2
    with pytest.raises(ExpiredData):
        final_live(t, "true", NOW)
    assert final_live(t, "level = 'WARN' and ts > timestamp_ntz'2024-02-08'", NOW).count() == 1
    assert purge(t, NOW, "level = 'DEBUG'")["rows"] == 1
    assert {r.state: r.n for r in row_state(t, NOW).collect()} == {"not expired": 2, "expired": 1, "purged": 1}
    assert changes(db.rel("logs")).filter("_action = 'DELETE'").count() == 0
    from standq.scratch import scratch

    cold = scratch(spark)
    assert purge(t, NOW, archive=cold)["rows"] == 1 and spark.read.parquet(cold).count() == 1
    set_policy(t, None, "drop")
    assert live(t, NOW).count() == 2


@pytest.mark.parametrize(
    ("where", "purged"),
    [
        ("ts >= timestamp_ntz'2024-01-03' and ts < timestamp_ntz'2024-01-05'", True), ("ts < timestamp_ntz'2024-01-03' and value > 5", True), ("value = 4", True), ("abs(value) = 4", True),
        ("value > 10", False), ("ts >= timestamp_ntz'2024-01-11' and value > 5", False), ("level = 'WARN'", False), ("value > 10 or ts < timestamp_ntz'2024-01-05'", True), ("level > 5", True),
        ("note = 'a and value > 10'", True), ("note = 'b'", False),
    ],
)
def test_purged_box(db, spark, where, purged):
    db.create_table("logs", "level string, ts timestamp_ntz, value int, note string", insert_only=True, expire="level = 'DEBUG'")
    rows = [("DEBUG", datetime(2024, 1, d), d, "a and value > 10") for d in range(1, 11)]
    with db.transaction() as tx:
        tx.insert("logs", spark.createDataFrame(rows, "level string, ts timestamp_ntz, value int, note string"))
    t = db.table("logs")
    assert purge(t, NOW)["rows"] == 10
    if purged:
        with pytest.raises(ExpiredData):
            final_live(t, where, NOW)
    else:
        assert final_live(t, where, NOW).count() == 0


def test_ranges(spark):
    rows = spark.createDataFrame([(i, None if i == 3 else float(i), datetime(2024, 1 + i % 12, 5)) for i in range(12)], "i int, x double, t timestamp_ntz")
    assert window_table(rows, "i", 2, 5).count() == 6  # gaps
    assert window_table(rows, "x", 4.0, 2.0).filter("x = 9").count() == 2
    assert window_table(rows, "x", 4.0, 2.0).filter("x is null").count() == 0
    by_month = window_table(rows, "t", Months(3), Months(1), datetime(2024, 1, 1))
    assert by_month.filter("i = 6").select(F.date_format("win_start", "MM")).toPandas().iloc[:, 0].tolist() == ["05", "06", "07"]
    ways = [hop_aggregate(rows, "t", [], {"n": ("count", "i"), "s": ("sum", "i"), "lo": ("min", "i"), "hi": ("max", "i")}, timedelta(days=40), timedelta(days=15), datetime(2024, 1, 3), s) for s in ("panes", "explode", "native")]
    got = [sorted(map(tuple, w.collect())) for w in ways]
    assert got[0] == got[1] == got[2] and got[0]
    with pytest.raises(ValueError):
        window_table(rows, "i", 0)


def test_watermarks(spark):
    rows = spark.createDataFrame([("a", 1), ("a", 9), ("b", 4)], "s string, t int")
    assert Watermark.by(rows, "t", ["s"]).value == 4
    first = Watermark.percentile(rows.withColumn("t", F.col("t").cast("double")), "t", 0.5)
    again = Watermark.percentile(spark.createDataFrame([(0.0,)], "t double"), "t", 0.5, first)
    assert again.value == first.value
    assert bucket_upper_bound("date_trunc('hour', t)", "t") and bucket_upper_bound("sin(t)", "t") is None
    assert Watermark(None).final_rows(rows, "t").count() == 0


def test_percentile_is_the_value_of_its_rank(spark, monkeypatch):
    for exact in (100_000, 50):
        monkeypatch.setattr(final, "EXACT", exact)
        for rows, p in ((spark.range(20_011).selectExpr("id * 7919 % 20011 AS t"), 0.95), (spark.range(3_000).selectExpr("id % 4 AS t"), 0.5), (spark.range(1).selectExpr("id AS t"), 0.95)):
            held = sorted(r.t for r in rows.collect())
            want = held[max(1, math.ceil(Fraction(str(p)) * len(held))) - 1]
            assert Watermark.percentile(rows, "t", p, accuracy=20).value == want
    assert Watermark.percentile(spark.createDataFrame([(None,)], "t bigint"), "t", 0.5).value is None


def test_statements(db, spark):
    s, seen = Session(db), []
    s.execute("CREATE TABLE st (id INT, at TIMESTAMP_NTZ, v INT) INSERT ONLY INCREASING (at) GRACE INTERVAL '10' SECOND")
    assert db.metas["st"].insert_only and db.metas["st"].increasing["at"]["grace"]["v"] == 10
    s.execute("CREATE TABLE copy (id INT, v INT, CHECK (v < 100)) INSERT ONLY")
    s.execute("CREATE TABLE bad (tag STRING, reason STRING, row_json STRING)")
    s.execute("CREATE TASK c SCHEDULE ON COMMIT OR EVERY 5 MINUTES LOG ERRORS INTO bad AS INSERT INTO copy SELECT CONTINUOUS id, v FROM CHANGES(st)" .replace("CHANGES(st)", "st"))
    sub = s.execute("SUBSCRIBE TO SELECT id FROM CHANGES(st, 'DELTA') WHERE v > 1", lambda df: seen.extend(r.id for r in df.collect()))
    s.execute("INSERT INTO st VALUES (1, timestamp_ntz'2024-01-01 00:00:00', 1), (2, timestamp_ntz'2024-01-01 00:00:05', 2), (3, timestamp_ntz'2024-01-01 00:00:06', 500)")
    assert sorted(seen) == [2, 3] and s.execute("SELECT * FROM copy").count() == 2 and s.execute("SELECT * FROM bad").count() == 1
    sub.cancel()
    s.execute("CONTINUOUS CURSOR cur IS SELECT * FROM st WHERE v = 2")
    assert s.execute("FETCH NEXT FROM cur").df.count() == 1
    s.execute("CLOSE cur")
    s.execute("ALTER TASK c PAUSE")
    s.execute("ALTER TASK c RESUME")
    s.execute("DROP TASK c")
    s.execute("CREATE TABLE kv (k STRING, v INT, PRIMARY KEY (k))")
    s.execute("INSERT INTO kv VALUES ('a', 1), ('b', 2)")
    s.execute("UPDATE kv SET v = v + 1 WHERE k = 'a'")
    s.execute("DELETE FROM kv WHERE k = 'b'")
    assert [tuple(r) for r in s.execute("SELECT k, v FROM kv").collect()] == [("a", 2)]
    s.execute("ALTER TABLE st ADD EXPIRE WHERE at < now() - interval '1' day")
    s.execute("ALTER TABLE st DROP EXPIRE")
    s.execute("ALTER TABLE kv ADD INSERT ONLY")
    s.execute("ALTER TABLE kv DROP INSERT ONLY")
    assert s.execute("SELECT FINAL * FROM st").count() == 3
    with pytest.raises(StandingQueryError):
        s.execute("CREATE TABLE x (a INT) ODD THING")


def test_concurrent_commit(db, spark):
    from standq.sources.store import Transaction

    db.create_table("t", "id int")
    one, two = Transaction(db), Transaction(db)
    for tx in (one, two):
        tx.insert("t", spark.range(1).selectExpr("cast(id as int) id"))
    one.commit()
    with pytest.raises(ConcurrentCommit):
        two.commit()


def test_commit_ticker(db, spark):
    from standq.scratch import scratch
    from standq.sources.files import commit_stream

    db.create_table("t", "id int")
    with db.transaction() as tx:
        tx.insert("t", spark.range(1).selectExpr("cast(id as int) id"))
    got = scratch(spark)
    q = commit_stream(spark, db.root).writeStream.foreachBatch(lambda df, n: df.write.mode("append").parquet(got)).option("checkpointLocation", scratch(spark)).start()
    try:
        q.processAllAvailable()
    finally:
        q.stop()
    assert [r.commit_no for r in spark.read.parquet(got).collect()] == [1]


def rows_of(df):
    columns = sorted(df.columns)
    one = lambda v: repr(round(float(v), 6)) if isinstance(v, float) else str(v)
    return sorted(tuple(one(v) if v is not None and v == v else "-" for v in r) for r in df[columns].astype(object).itertuples(index=False))


@pytest.mark.parametrize("name", ["hop_final", "hop_changes", "scd_join_both", "top10_customers", "agg_outstanding_partials", "watermark_final_minute", "late_side_table", "expire_matrix", "as_of_join", "range_join", "stop_resume", "hop_streaming_append", "numeric_window", "month_window"])
def test_workload_against_sql(spark, name):
    """The driver compares all; these are one of each kind, at the smallest scale."""
    import os

    con = duckdb.connect()
    for t in os.listdir(SF):
        con.sql(f"CREATE VIEW {t[:-8]} AS SELECT * FROM '{SF}/{t}'")
    assert rows_of(queries()[name](spark, SF).toPandas()) == rows_of(con.sql(oracles()[name]).df())


def test_numeric_finals_plan_is_pruned(spark):
    """The frontier reaches the scan, and only the columns asked for are read."""
    from standq.workloads.fixtures import ev
    from standq.workloads.flows import final_window

    plan = final_window(ev(spark, SF)).delta(5, 6)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(ts), LessThan(ts," in plan and "props" not in plan


def test_streaming_operators(spark, db):
    from standq.scratch import scratch
    from standq.streaming.final_stream import CommitFeed
    from standq.streaming.operators import dedup_within, interval_join, split_late

    kind = spark.createDataFrame([], "id int, ts timestamp_ntz, v int").schema
    at = lambda s: datetime(2024, 1, 1, 0, 0, s)
    feed = CommitFeed(spark, scratch(spark), kind)
    for rows in ([(1, at(0), 1), (1, at(1), 2)], [(1, at(2), 3), (2, at(3), 4)]):
        feed.push(spark.createDataFrame(rows, kind))
        feed.run(dedup_within(feed.stream(), "ts", ["id"], timedelta(seconds=30)), "append")
    assert sorted(r.id for r in spark.read.parquet(f"{feed.place}/out").collect()) == [1, 2]
    left, right = CommitFeed(spark, scratch(spark), kind), CommitFeed(spark, scratch(spark), kind)
    left.push(spark.createDataFrame([(1, at(0), 1), (2, at(0), 2)], kind))
    right.push(spark.createDataFrame([(1, at(4), 7), (2, at(30), 8)], kind))
    b = right.stream().withColumnRenamed("ts", "other").withColumnRenamed("v", "w")
    left.run(interval_join(left.stream(), b, "id", "ts", "other", timedelta(seconds=5), timedelta(seconds=10)), "append")
    assert [(r.id, r.w) for r in spark.read.parquet(f"{left.place}/out").collect()] == [(1, 7)]
    ok, late = split_late(spark.createDataFrame([(1, at(1), 1), (2, at(9), 1)], kind), "ts", at(5))
    assert [r.id for r in ok.collect()] == [2] and [r.id for r in late.collect()] == [1]


def test_range_function(spark):
    from standq.functions.ranges import register_range_function

    register_range_function(spark)
    assert [r.i for r in spark.sql("SELECT * FROM range_numbers(9.0D, 5.0D, 2.0D, 0.0D)").collect()] == [3, 4]
    assert [r.i for r in spark.sql("SELECT * FROM range_numbers(4.0D, 5.0D, 2.0D, 0.0D)").collect()] == [0, 1, 2]


def test_measures(db, spark):
    from standq import measures
    from standq.operators.task import Task

    db.create_table("ev", "id int", insert_only=True)
    db.create_table("copy", "id int", insert_only=True)
    Task.insert(db, "c", db.rel("ev"), "copy")

    def commit():
        with db.transaction() as tx:
            tx.insert("ev", spark.createDataFrame([(1,), (2,)], "id int"))

    got = measures.commit_delay(db, commit)
    assert 0 < got["tasks_s"] < got["commit_s"]
    assert measures.check_subset(db.rel("ev"), 0, db.version) and measures.staleness(db, "ev", 0) == 1
    assert measures.applied_twice_or_never(db.table("ev").snapshot(), db.table("copy").snapshot(), ["id"]) == {"twice": 0, "never": 0}
    assert measures.sync_error(db.table("copy").snapshot(), db.table("ev").snapshot()) == 0
    assert measures.compaction_ratio(db.table("ev")) == {"log": 2, "delta": 2}


def test_procedures(db, spark):
    s = Session(db)
    s.execute("CREATE TABLE ev (id INT) INSERT ONLY")
    s.execute("INSERT INTO ev VALUES (1)")
    from standq.operators.cursor import ContinuousCursor

    assert s.call(lambda s: ContinuousCursor(db.rel("ev"), with_return=True)).df.count() == 1
    with pytest.raises(StandingQueryError):
        s.call(lambda s: ContinuousCursor(db.rel("ev")))


@pytest.mark.parametrize("name", ["two_writers", "cursor_from_time", "insert_only_proofs"])
def test_results_follow_the_given_tables(spark, name, tmp_path):
    """On other rows there is another result, and it is that of the SQL."""
    con = duckdb.connect()
    for t, where in (("events", "event_id % 3 <> 0"), ("customer", "c_custkey % 2 = 0")):
        spark.read.parquet(f"{SF}/{t}.parquet").filter(where).write.parquet(f"{tmp_path}/{t}.parquet")
        con.sql(f"CREATE VIEW {t} AS FROM '{tmp_path}/{t}.parquet/*.parquet'")
    got = sorted(map(tuple, queries()[name](spark, str(tmp_path)).collect()))
    assert got == sorted(con.sql(oracles()[name]).fetchall())
    assert got != sorted(map(tuple, queries()[name](spark, SF).collect()))


def test_entry_without_the_llm_folders():
    import subprocess
    import sys
    from pathlib import Path

    code = (
        "import sys; sys.modules['standq.llm'] = None; sys.modules['corpus_pipeline'] = None; import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); "
        "assert 'hop_final' in q and 'pipeline' not in q and not any(k[:2] == 'op' and k[2].isdigit() for k in q) and set(o) <= set(q)"
    )
    subprocess.run([sys.executable, "-c", code], cwd=Path(__file__).resolve().parents[1], check=True)

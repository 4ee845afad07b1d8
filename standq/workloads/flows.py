"""Cursors, changes and window workloads."""

from __future__ import annotations

from datetime import datetime, timedelta

from pyspark.sql import functions as F

from standq.functions.compaction import compact_delete_insert, compact_net, compact_update, encode
from standq.functions.ranges import Months
from standq.operators.cursor import ContinuousCursor
from standq.operators.final import FinalWindow, rewrite_windows
from standq.operators.windows import hop_aggregate, session_table, window_table
from standq.plans.relation import changes
from standq.workloads.fixtures import CUST_FINAL, cust, ev, ev_grace, fresh, read
from standq.workloads.registry import workload

EV = "(SELECT *, CAST(1 + floor((day(ts) - 1) / 5) AS BIGINT) AS c FROM events)"
MONEY = "cast(value as decimal(18,4))"
STAMP = "yyyy-MM-dd HH:mm:ss"


def stamp(c: str, name: str | None = None):
    return F.date_format(F.col(c), STAMP).alias(name or c)


def stamped(c: str) -> str:
    return f"strftime({c}, '%Y-%m-%d %H:%M:%S')"


def hops(size: str, step: str, start: str = "TIMESTAMP '2024-01-01'", rows: str = "events", col: str = "ts") -> str:
    """DuckDB: rows with the start s and end e of every range that holds them; sizes in whole seconds."""
    return f"""(SELECT r.*, {start} + to_seconds(i * {step}) AS s, {start} + to_seconds(i * {step} + {size}) AS e
      FROM {rows} r, unnest(range(CAST(greatest(0, floor((date_diff('microsecond', {start}, {col}) / 1e6 - {size}) / {step}) + 1) AS BIGINT),
                                  CAST(floor(date_diff('microsecond', {start}, {col}) / 1e6 / {step}) AS BIGINT) + 1)) AS u(i))"""


@workload("select_all_table", "SELECT event_id, user_id, event_type, value FROM events")
def select_all_table(spark, sf):
    return ev(spark, sf).rel("ev").to_df().select("event_id", "user_id", "event_type", "value")


@workload("subscribe_all", f"SELECT event_id, value, c AS fetch_no FROM {EV}")
def subscribe_all(spark, sf):
    db = ev(spark, sf)
    cursor, out = ContinuousCursor(db.rel("ev")), None
    for n in range(1, db.version + 1):
        part = cursor.fetch(max_commits=1).df.select("event_id", "value", F.lit(n).cast("long").alias("fetch_no"))
        out = part if out is None else out.unionByName(part)
    cursor.close()
    return out


@workload("cursor_second_fetch", f"SELECT event_id, value FROM {EV} WHERE c = 2")
def cursor_second_fetch(spark, sf):
    cursor = ContinuousCursor(ev(spark, sf).rel("ev"))
    cursor.fetch(max_commits=1)
    return cursor.fetch(max_commits=1).df.select("event_id", "value")


@workload("cursor_from_bookmark", f"SELECT event_id, value FROM {EV} WHERE c >= 4")
def cursor_from_bookmark(spark, sf):
    return ContinuousCursor(ev(spark, sf).rel("ev"), start_at=3).fetch().df.select("event_id", "value")


@workload(
    "avg_delta",
    f"""WITH p AS (SELECT c, sum({MONEY}) AS s, count(*) AS n FROM {EV} GROUP BY c),
    r AS (SELECT c, round(CAST(sum(s) OVER w AS DOUBLE) / sum(n) OVER w, 6) AS a FROM p WINDOW w AS (ORDER BY c)),
    l AS (SELECT c, a, lag(a) OVER (ORDER BY c) AS b FROM r)
    SELECT c AS commit_no, 1 AS sign, a AS avg_value FROM l WHERE b IS NULL OR a <> b
    UNION ALL SELECT c, -1, b FROM l WHERE b IS NOT NULL AND a <> b""",
)
def avg_delta(spark, sf):
    db = ev(spark, sf)
    # the state between answers is one row of sums: only each commit's rows are read
    rows = db.table("ev").log_slice().groupBy("_commit_no").agg(F.expr(f"sum({MONEY})").alias("s"), F.count("*").alias("n")).orderBy("_commit_no").collect()
    out, s, n, before = [], 0, 0, None
    for r in rows:  # one row a commit
        s, n = s + r.s, n + r.n
        now = round(float(s) / n, 6)
        if now != before:
            out += [(r._commit_no, -1, before)] if before is not None else []
            out.append((r._commit_no, 1, now))
        before = now
    return spark.createDataFrame(out, "commit_no long, sign int, avg_value double")


HOP_SUM = f"SELECT event_type, s, e, CAST(sum({MONEY}) AS DOUBLE) AS total, count(*) AS n FROM {hops('432000', '172800')} GROUP BY event_type, s, e"
SIZE, STEP, START = timedelta(days=5), timedelta(days=2), datetime(2024, 1, 1)
SUMS = {"total": ("sum", MONEY), "n": ("count", "value")}


def shown(df):
    return df.select("event_type", stamp("win_start"), stamp("win_end"), F.col("total").cast("double").alias("total"), F.col("n").cast("long").alias("n"))


@workload("hop_sum_5d_2d", f"SELECT event_type, {stamped('s')} AS win_start, {stamped('e')} AS win_end, total, n FROM ({HOP_SUM})")
def hop_sum(spark, sf):
    return shown(hop_aggregate(ev(spark, sf).rel("ev").to_df(), "ts", ["event_type"], SUMS, SIZE, STEP, START, "panes"))


@workload("hop_sum_explode", f"SELECT event_type, {stamped('s')} AS win_start, {stamped('e')} AS win_end, total, n FROM ({HOP_SUM})")
def hop_sum_explode(spark, sf):
    return shown(hop_aggregate(ev(spark, sf).rel("ev").to_df(), "ts", ["event_type"], SUMS, SIZE, STEP, START, "explode"))


@workload("hop_sum_native", f"SELECT event_type, {stamped('s')} AS win_start, {stamped('e')} AS win_end, total, n FROM ({HOP_SUM})")
def hop_sum_native(spark, sf):
    return shown(hop_aggregate(ev(spark, sf).rel("ev").to_df(), "ts", ["event_type"], SUMS, SIZE, STEP, START, "native"))


@workload(
    "hop_avg_30s",
    f"SELECT {stamped('s')} AS win_start, round(CAST(sum({MONEY}) AS DOUBLE) / count(*), 6) AS avg_value FROM {hops('30', '10')} GROUP BY s",
)
def hop_avg(spark, sf):
    made = hop_aggregate(ev(spark, sf).rel("ev").to_df(), "ts", [], SUMS, timedelta(seconds=30), timedelta(seconds=10), START)
    return made.select(stamp("win_start"), F.round(F.col("total").cast("double") / F.col("n"), 6).alias("avg_value"))


CLOSED = f"SELECT event_type, {stamped('s')} AS win_start, {stamped('e')} AS win_end, total, n FROM ({HOP_SUM}) WHERE e <= (SELECT max(ts) FROM events)"


def final_window(db, **options):
    return FinalWindow(db.rel("ev"), "ts", ["event_type"], SUMS, SIZE, STEP, START, **options)


@workload("hop_final", CLOSED)
def hop_final(spark, sf):
    return shown(final_window(ev(spark, sf)).to_df())


@workload("hop_final_grace1d", CLOSED.replace("(SELECT max(ts) FROM events)", "(SELECT max(ts) - INTERVAL 1 DAY FROM events)"))
def hop_final_grace(spark, sf):
    return shown(final_window(ev_grace(spark, sf)).to_df())


@workload("hop_final_fetches", CLOSED)
def hop_final_fetches(spark, sf):
    """The union of all fetches of a cursor over FINAL: no range twice, none missing."""
    db = ev(spark, sf)
    cursor, out = ContinuousCursor(final_window(db), rules="extended"), None
    for _ in range(db.version):
        part = cursor.fetch(max_commits=1).df
        out = part if out is None else out.unionByName(part)
    cursor.close()
    return shown(out)


@workload("hop_final_literal", CLOSED.replace("WHERE e <=", "WHERE e <"))
def hop_final_literal(spark, sf):
    return shown(final_window(ev(spark, sf), closure="literal").to_df())


@workload("final_equals_final_changes", f"SELECT 0 AS differing, (SELECT count(*) FROM ({CLOSED})) AS closed_ranges")
def final_equals(spark, sf):
    db = ev(spark, sf)
    plain = shown(final_window(db).to_df())
    parts = [shown(final_window(db).delta(v, v + 1)) for v in range(db.version)]
    other = parts[0]
    for p in parts[1:]:
        other = other.unionByName(p)
    diff = plain.exceptAll(other).unionByName(other.exceptAll(plain))
    return diff.agg(F.count("*").cast("int").alias("differing")).crossJoin(plain.agg(F.count("*").alias("closed_ranges")))


HOP_CHANGES = f"""
  WITH h AS {hops('432000', '172800', rows=EV)},
  g AS (SELECT event_type, s, c, sum({MONEY}) AS t FROM h GROUP BY event_type, s, c),
  r AS (SELECT event_type, s, c, CAST(sum(t) OVER w AS DOUBLE) AS a, CAST(sum(t) OVER w - t AS DOUBLE) AS b, row_number() OVER w AS k FROM g WINDOW w AS (PARTITION BY event_type, s ORDER BY c))
  SELECT event_type, {stamped('s')} AS win_start, c AS commit_no, 1 AS sign, a AS total FROM r WHERE k = 1 OR a <> b
  UNION ALL SELECT event_type, {stamped('s')}, c, -1, b FROM r WHERE k > 1 AND a <> b"""


@workload("hop_changes", HOP_CHANGES)
def hop_changes(spark, sf):
    """Every correction of every range: the change of a windowed aggregate, commit by commit."""
    db = ev(spark, sf)
    query = db.rel("ev").window("ts", SIZE, STEP, START).aggregate(["event_type", "win_start", "win_end"], total=f"cast(sum({MONEY}) as double)")
    made = changes(query, format="LOG", encoding="delete_insert")
    return made.select("event_type", stamp("win_start"), F.col("_commit_no").alias("commit_no"), F.when(F.col("_action") == "DELETE", -1).otherwise(1).alias("sign"), "total")


HOUR = "TIMESTAMP '2024-01-01'"
TUMBLE = f"""SELECT user_id, {stamped('s')} AS win_start, {stamped('e')} AS win_end, count(*) AS n FROM {hops('3600', '3600', rows="(SELECT * FROM events WHERE event_type = 'purchase')")}
  WHERE e + INTERVAL 10 SECOND <= (SELECT max(ts) FROM events WHERE event_type = 'purchase') GROUP BY user_id, s, e"""
HOP_HOUR = TUMBLE.replace(hops("3600", "3600", rows="(SELECT * FROM events WHERE event_type = 'purchase')"), hops("3600", "600", rows="(SELECT * FROM events WHERE event_type = 'purchase')"))
TEN = timedelta(seconds=10)


def hour_shown(df):
    return df.select("user_id", stamp("win_start"), stamp("win_end"), F.col("n").cast("long").alias("n"))


def purchases(db):
    """A table of purchases alone, for FINAL needs a table's own maximum."""
    from standq.operators.constraints import Increasing

    spark = db.spark
    out = fresh(spark)
    out.create_table("ev", db.table("ev").schema, ["event_id"], True, [Increasing("ts")])
    out.ingest_history("ev", db.table("ev").snapshot().filter("event_type = 'purchase'"), F.expr("1 + floor((day(ts) - 1) / 5)"))
    return out


@workload("tumble_hour_final", TUMBLE)
def tumble_final(spark, sf):
    rel = FinalWindow(purchases(ev(spark, sf)).rel("ev"), "ts", ["user_id"], {"n": ("count", "event_id")}, timedelta(hours=1), None, START, TEN)
    return hour_shown(rel.to_df())


@workload("tumble_hour_rewrite", TUMBLE)
def tumble_rewrite(spark, sf):
    rows = ev(spark, sf).table("ev").snapshot().filter("event_type = 'purchase'")
    return hour_shown(rewrite_windows(rows, "ts", ["user_id"], [F.count("*").alias("n")], timedelta(hours=1), None, START, TEN))


@workload("hop_hour_10m_final", HOP_HOUR)
def hop_hour_final(spark, sf):
    rel = FinalWindow(purchases(ev(spark, sf)).rel("ev"), "ts", ["user_id"], {"n": ("count", "event_id")}, timedelta(hours=1), timedelta(minutes=10), START, TEN)
    return hour_shown(rel.to_df())


@workload("hop_hour_10m_rewrite", HOP_HOUR)
def hop_hour_rewrite(spark, sf):
    rows = ev(spark, sf).table("ev").snapshot().filter("event_type = 'purchase'")
    return hour_shown(rewrite_windows(rows, "ts", ["user_id"], [F.count("*").alias("n")], timedelta(hours=1), timedelta(minutes=10), START, TEN))


@workload("gapped_window", f"SELECT {stamped('s')} AS win_start, count(*) AS n FROM {hops('3600', '10800')} GROUP BY s")
def gapped_window(spark, sf):
    rows = window_table(read(spark, sf, "events"), "ts", timedelta(hours=1), timedelta(hours=3), START)
    return rows.groupBy("win_start").agg(F.count("*").alias("n")).select(stamp("win_start"), "n")


@workload(
    "numeric_window",
    f"""SELECT i * 200 AS win_start, i * 200 + 500 AS win_end, CAST(sum({MONEY}) AS DOUBLE) AS total FROM events,
    unnest(range(greatest(0, (event_id - 500) // 200 + CASE WHEN event_id < 500 AND (event_id - 500) % 200 <> 0 THEN 0 ELSE 1 END), event_id // 200 + 1)) AS u(i)
    WHERE event_id >= i * 200 AND event_id < i * 200 + 500 GROUP BY i""",
)
def numeric_window(spark, sf):
    rows = window_table(read(spark, sf, "events"), "event_id", 500, 200)
    return rows.groupBy("win_start", "win_end").agg(F.expr(f"cast(sum({MONEY}) as double)").alias("total"))


@workload(
    "month_window",
    """SELECT strftime(DATE '1995-01-01' + to_months(CAST(i AS INTEGER)), '%Y-%m-%d') AS win_start, count(*) AS n
    FROM (SELECT (year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 AS m FROM orders), unnest(range(greatest(0, m - 2), m + 1)) AS u(i) GROUP BY i""",
)
def month_window(spark, sf):
    rows = window_table(read(spark, sf, "orders"), "o_orderdate", Months(3), Months(1), datetime(1995, 1, 1))
    return rows.groupBy("win_start").agg(F.count("*").alias("n")).select(F.date_format("win_start", "yyyy-MM-dd").alias("win_start"), "n")


@workload(
    "session_gap",
    f"""WITH l AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS g FROM events),
    s AS (SELECT user_id, ts, sum(g) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM l)
    SELECT user_id, {stamped('min(ts)')} AS win_start, count(*) AS n FROM s GROUP BY user_id, k""",
)
def session_gap(spark, sf):
    made = session_table(read(spark, sf, "events"), "ts", "6 hours", ["user_id"], [F.count("*").alias("n")])
    return made.select("user_id", stamp("win_start"), "n")


# Changes of a mutated table

BASE = "SELECT c_custkey AS k, c_acctbal AS a, c_mktsegment AS m FROM customer"
A2 = "round(a + 100, 2)"
LOG = f"""
  SELECT k, a, m, 1 AS commit_no, 'INSERT' AS action FROM ({BASE})
  UNION ALL SELECT k, {A2}, 'BUILDING', 2, 'UPDATE' FROM ({BASE}) WHERE k % 7 = 0
  UNION ALL SELECT k, CASE WHEN k % 7 = 0 THEN {A2} ELSE a END, CASE WHEN k % 7 = 0 THEN 'BUILDING' ELSE m END, 3, 'DELETE' FROM ({BASE}) WHERE k % 11 = 0
  UNION ALL SELECT k, a, m, 4, 'INSERT' FROM ({BASE}) WHERE k % 22 = 0
  UNION ALL SELECT k, CASE WHEN k % 22 = 0 THEN round(a + 50, 2) ELSE round({A2} + 50, 2) END, CASE WHEN k % 22 = 0 THEN m ELSE 'BUILDING' END, 5, 'UPDATE' FROM ({BASE}) WHERE k % 7 = 0 AND (k % 11 <> 0 OR k % 22 = 0)
  UNION ALL SELECT k + 1000000000, a, m, 5, x FROM ({BASE}), (VALUES ('INSERT'), ('DELETE')) v(x) WHERE k % 50 = 0"""


def cust_columns(df, *more):
    return df.select(F.col("c_custkey").alias("k"), F.col("c_acctbal").alias("a"), F.col("c_mktsegment").alias("m"), F.col("_action").alias("action"), *more)


@workload("changes_log", LOG)
def changes_log(spark, sf):
    return cust_columns(changes(cust(spark, sf).rel("cust"), format="LOG", encoding="single"), F.col("_commit_no").cast("int").alias("commit_no"))


@workload("changes_delta", f"SELECT c_custkey AS k, c_acctbal AS a, c_mktsegment AS m, 'INSERT' AS action FROM ({CUST_FINAL})")
def changes_delta(spark, sf):
    return cust_columns(changes(cust(spark, sf).rel("cust")))


# commits 2 to 4 on balance: raised rows are updates, deleted ones deletes (with the image before), those back inserts
RANGE = f"""
  SELECT k, {A2} AS a, 'BUILDING' AS m, 'UPDATE' AS action FROM ({BASE}) WHERE k % 7 = 0 AND k % 11 <> 0
  UNION ALL SELECT k, a, m, 'DELETE' FROM ({BASE}) WHERE k % 11 = 0
  UNION ALL SELECT k, a, m, 'INSERT' FROM ({BASE}) WHERE k % 22 = 0"""


@workload("changes_range", RANGE)
def changes_range(spark, sf):
    return cust_columns(changes(cust(spark, sf).rel("cust"), 1, 4, encoding="single"))


@workload("changes_pair", RANGE + f" UNION ALL SELECT k, a, m, 'DELETE' FROM ({BASE}) WHERE k % 7 = 0 AND k % 11 <> 0")
def changes_pair(spark, sf):
    return cust_columns(changes(cust(spark, sf).rel("cust"), 1, 4, encoding="pair"))


@workload("changes_delete_insert", (RANGE + f" UNION ALL SELECT k, a, m, 'DELETE' FROM ({BASE}) WHERE k % 7 = 0 AND k % 11 <> 0").replace("'UPDATE'", "'INSERT'"))
def changes_delete_insert(spark, sf):
    return cust_columns(changes(cust(spark, sf).rel("cust"), 1, 4, encoding="delete_insert"))


@workload("changes_nested", f"SELECT k, a, m, commit_no, action AS inner_action, 'INSERT' AS action FROM ({LOG})")
def changes_nested(spark, sf):
    """The log of the log: everything in it was inserted."""
    outer = changes(cust(spark, sf).rel("cust").changes(format="LOG"), encoding="single")
    return outer.select(F.col("c_custkey").alias("k"), F.col("c_acctbal").alias("a"), F.col("c_mktsegment").alias("m"), F.col("commit_no").cast("int"), F.col("action").alias("inner_action"), F.col("_action").alias("action"))


@workload("changes_diff", RANGE)
def changes_diff(spark, sf):
    """The baseline: compare two states."""
    from standq.plans.relation import net_changes

    return cust_columns(net_changes(cust(spark, sf).rel("cust"), 1, 4, "diff"))


# last record of each row, per compaction family
LAST = f"SELECT c_custkey AS k, c_acctbal AS a, c_mktsegment AS m, 'INSERT' AS action FROM ({CUST_FINAL})"
GONE = f"""SELECT k, CASE WHEN k % 7 = 0 THEN {A2} ELSE a END AS a, CASE WHEN k % 7 = 0 THEN 'BUILDING' ELSE m END AS m, 'DELETE' AS action FROM ({BASE}) WHERE k % 11 = 0
  UNION ALL SELECT k + 1000000000, a, m, 'DELETE' FROM ({BASE}) WHERE k % 50 = 0"""


@workload("compact_net", LAST)
def compact_net_query(spark, sf):
    return cust_columns(compact_net(cust(spark, sf).table("cust").log_slice()))


@workload("compact_u", f"{LAST} UNION ALL {GONE}")
def compact_u(spark, sf):
    return cust_columns(compact_update(cust(spark, sf).table("cust").log_slice()))


@workload("compact_di", f"{LAST} UNION ALL {GONE}")
def compact_di(spark, sf):
    return cust_columns(compact_delete_insert(encode(cust(spark, sf).table("cust").log_slice(), "delete_insert")))

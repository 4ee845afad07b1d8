"""Constraint, finality, expiry, proof, streaming and measure workloads."""

from __future__ import annotations

from datetime import datetime, timedelta

from pyspark.sql import functions as F

from standq import measures
from standq.errors import ExpiredData
from standq.functions.ranges import Axis
from standq.operators.constraints import Increasing, Late, mark_late
from standq.operators.expire import compare_policies, final_live, live, purge, row_state, set_policy
from standq.operators.final import FinalWindow, Watermark, final
from standq.plans.prover import prove_insert_only
from standq.scratch import scratch
from standq.operators.windows import window_table
from standq.streaming.final_stream import CommitFeed, final_stream, verbose_stream, windowed_stream
from standq.streaming.operators import ROCKS, verbose_corrections
from standq.workloads.fixtures import EV_COMMIT, built, ev, ev_late, fresh, read
from standq.workloads.flows import CLOSED, EV, HOP_CHANGES, MONEY, SIZE, START, STEP, SUMS, hops, shown, stamp, stamped
from standq.workloads.registry import workload

LATE = "(SELECT *, epoch_us(ts) + ((event_id * 7919) % 1800 + CASE WHEN event_id % 97 = 0 THEN 172800 ELSE 0 END) * 1000000 AS arrival FROM events)"


def late_sql(grace: int, strict: bool = False, rows: str = LATE, c: str = "ts", order: str = "arrival, event_id", g: str | None = None) -> str:
    less = g if g is not None else f"- INTERVAL {grace} SECOND"
    return f"""SELECT count(*) FILTER (WHERE NOT late) AS accepted, count(*) FILTER (WHERE late) AS rejected FROM (
      SELECT coalesce({c} {'<=' if strict else '<'} max({c}) OVER (ORDER BY {order} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) {less}, false) AS late FROM {rows})"""


@workload("increasing_accept", f"SELECT c AS commit_no, count(*) AS accepted FROM {EV} GROUP BY c")
def increasing_accept(spark, sf):
    log = ev(spark, sf).table("ev").log_slice()
    return log.groupBy(F.col("_commit_no").alias("commit_no")).agg(F.count("*").alias("accepted"))


def judged(spark, sf, grace=None, strict=False):
    return measures.late_rows(mark_late(ev_late(spark, sf), "ts", ["arrival", "event_id"], grace, strict))


@workload("strict_reject", late_sql(0, True))
def strict_reject(spark, sf):
    return judged(spark, sf, strict=True)


@workload("grace_none", late_sql(0))
def grace_none(spark, sf):
    return judged(spark, sf)


@workload("grace_reject", late_sql(600))
def grace_reject(spark, sf):
    return judged(spark, sf, timedelta(minutes=10))


@workload("grace_accept", late_sql(1800))
def grace_accept(spark, sf):
    return judged(spark, sf, timedelta(minutes=30))


@workload("increasing_orders", late_sql(0, rows="orders", c="o_orderdate", order="o_orderkey", g=""))
def increasing_orders(spark, sf):
    return measures.late_rows(mark_late(read(spark, sf, "orders"), "o_orderdate", ["o_orderkey"]))


@workload("conv_turns", "SELECT count(*) - count(*) FILTER (WHERE late) AS accepted, count(*) FILTER (WHERE late) AS rejected FROM (SELECT coalesce(turn <= lag(turn) OVER (PARTITION BY conv_id ORDER BY turn), false) AS late FROM conversations)")
def conv_turns(spark, sf):
    return measures.late_rows(mark_late(read(spark, sf, "conversations"), "turn", ["turn"], strict=True, by=["conv_id"]))


BATCH = f"(SELECT *, CAST(floor((arrival - epoch_us(TIMESTAMP '2024-01-01')) / 432000000000) AS BIGINT) AS b FROM {LATE})"


@workload(
    "late_side_table",
    f"""WITH x AS (SELECT * FROM {BATCH}), m AS (SELECT b, max(max(ts)) OVER (ORDER BY b ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS top FROM x GROUP BY b)
    SELECT event_id, CASE WHEN top IS NOT NULL AND ts < top - INTERVAL 30 MINUTE THEN 'late' ELSE 'kept' END AS fate FROM x JOIN m USING (b)""",
)
def late_side_table(spark, sf):
    """Batches arrive one a commit; rows behind the frontier of the batches before go to a side table."""
    rows = ev_late(spark, sf).withColumn("b", F.floor((F.col("arrival") - F.unix_micros(F.lit(START).cast("timestamp"))) / 432_000_000_000))
    db = fresh(spark)
    kind = read(spark, sf, "events").schema
    db.create_table("ev", kind, ["event_id"], True, [Increasing("ts", grace=timedelta(minutes=30))])
    db.create_table("late", kind, ["event_id"], True)
    for r in rows.select("b").distinct().orderBy("b").collect():  # one row a batch
        with db.transaction() as tx:
            tx.insert("ev", rows.filter(F.col("b") == r.b), Late("side", "late"))
    kept = db.table("ev").snapshot().select("event_id", F.lit("kept").alias("fate"))
    return kept.unionByName(db.table("late").snapshot().select("event_id", F.lit("late").alias("fate")))


@workload("ledger_closed", "SELECT o_orderkey, o_totalprice FROM orders WHERE o_orderdate < TIMESTAMP '2000-01-01'")
def ledger_closed(spark, sf):
    """Closed books: rows before the date are final; FINAL gives them alone."""

    def make(spark, sf):
        db = fresh(spark)
        db.create_table("ord", read(spark, sf, "orders").schema, ["o_orderkey"])
        with db.transaction() as tx:
            tx.insert("ord", read(spark, sf, "orders"))
        db.table("ord").set_finalize("o_orderdate < timestamp_ntz'2000-01-01 00:00:00'")
        return db

    return final(built(spark, sf, "ledger", make).rel("ord")).select("o_orderkey", "o_totalprice")


WM = "(SELECT max(d) + INTERVAL 85800 SECOND FROM (SELECT DISTINCT date_trunc('day', ts) AS d FROM events) WHERE d < (SELECT max(date_trunc('day', ts)) FROM events))"


@workload(
    "watermark_final_minute",
    f"SELECT event_type, strftime(date_trunc('minute', ts), '%Y-%m-%d %H:%M:%S') AS minute, CAST(sum({MONEY}) AS DOUBLE) AS total FROM events WHERE ts < {WM} AND date_trunc('minute', ts) + INTERVAL 1 MINUTE <= {WM} GROUP BY 1, date_trunc('minute', ts)",
)
def watermark_final_minute(spark, sf):
    """Another stream says how far the first is complete: a row a day, 23:50 of it, once the next day has begun."""

    def make(spark, sf):
        db, rows = fresh(spark), read(spark, sf, "events")
        db.create_table("ev", rows.schema, ["event_id"], True, [Increasing("ts")])
        db.create_table("wm", "wm timestamp_ntz", insert_only=True, increasing=[Increasing("wm")])
        db.ingest_history("ev", rows, F.expr(EV_COMMIT))
        days = rows.select(F.date_trunc("day", "ts").cast("timestamp_ntz").alias("d")).distinct()
        last = days.agg(F.max("d")).first()[0]
        with db.transaction() as tx:
            tx.insert("wm", days.filter(F.col("d") < F.lit(last)).select((F.col("d") + F.expr("interval '23:50:00' hour to second")).alias("wm")))
        return db

    db = built(spark, sf, "watermark", make)
    made = Watermark.from_table(db.table("wm"), "wm").final_groups(db.table("ev").snapshot(), "ts", "date_trunc('minute', ts)", ["event_type"], [F.expr(f"cast(sum({MONEY}) as double)").alias("total")])
    return made.select("event_type", stamp("bucket", "minute"), "total")


@workload("percentile_watermark", "SELECT event_id FROM events WHERE ts < (SELECT quantile_disc(ts, 0.95) FROM events)")
def percentile_watermark(spark, sf):
    rows = read(spark, sf, "events")
    return Watermark.percentile(rows, "ts", 0.95, accuracy=1_000_000).final_rows(rows, "ts").select("event_id")


@workload("multi_watermark", "SELECT event_id FROM events WHERE ts < (SELECT min(m) FROM (SELECT max(ts) AS m FROM events GROUP BY event_type))")
def multi_watermark(spark, sf):
    rows = read(spark, sf, "events")
    return Watermark.by(rows, "ts", ["event_type"]).final_rows(rows, "ts").select("event_id")


# Expiration

DAILY = "event_type = 'error' and ts < now() - interval '1' day"
MODIFIED = f"{DAILY} or event_type = 'view' and ts < now() - interval '7' day"
GONE1 = "(event_type = 'error' AND ts < (SELECT max(ts) FROM events) - INTERVAL 1 DAY)"
GONE7 = f"({GONE1} OR (event_type = 'view' AND ts < (SELECT max(ts) FROM events) - INTERVAL 7 DAY))"


def last_time(spark, sf) -> datetime:
    return read(spark, sf, "events").agg(F.max("ts")).first()[0]


def expiring(spark, sf):
    from standq.workloads.fixtures import make_ev

    return make_ev(spark, sf)


@workload("expire_daily", f"SELECT event_id FROM events WHERE NOT {GONE1}")
def expire_daily(spark, sf):
    table = expiring(spark, sf).table("ev")
    set_policy(table, DAILY)
    return live(table, last_time(spark, sf)).select("event_id")


@workload("expire_modify", f"SELECT event_id FROM events WHERE NOT {GONE7}")
def expire_modify(spark, sf):
    table = expiring(spark, sf).table("ev")
    set_policy(table, DAILY)
    set_policy(table, MODIFIED, "modify")
    return live(table, last_time(spark, sf)).select("event_id")


@workload("expire_drop", "SELECT event_id FROM events")
def expire_drop(spark, sf):
    table = expiring(spark, sf).table("ev")
    set_policy(table, DAILY)
    set_policy(table, None, "drop")
    return live(table, last_time(spark, sf)).select("event_id")


PURGED = "ts < timestamp_ntz'2024-01-11 00:00:00'"


@workload(
    "expire_regions",
    f"SELECT CASE WHEN {GONE1} AND ts < TIMESTAMP '2024-01-11' THEN 'purged' WHEN {GONE1} THEN 'expired' ELSE 'not expired' END AS state, count(*) AS n FROM events GROUP BY 1",
)
def expire_regions(spark, sf):
    table, now = expiring(spark, sf).table("ev"), last_time(spark, sf)
    set_policy(table, DAILY)
    purge(table, now, PURGED)
    return row_state(table, now)


@workload(
    "expire_matrix",
    "SELECT * FROM (VALUES ('live only', 'ok'), ('live and expired', 'error'), ('expired only', 'error'), ('expired and purged', 'error'), ('all', 'error')) AS v(query, outcome)",
)
def expire_matrix(spark, sf):
    """FINAL opts in to the error: only a query that touches live rows alone is answered."""
    table, now = expiring(spark, sf).table("ev"), last_time(spark, sf)
    set_policy(table, DAILY)
    purge(table, now, PURGED)
    out = []
    for name, where in (
        ("live only", "event_type = 'view'"), ("live and expired", "event_type in ('view', 'error') and ts >= timestamp_ntz'2024-01-15 00:00:00'"),
        ("expired only", "event_type = 'error' and ts >= timestamp_ntz'2024-01-15 00:00:00' and ts < timestamp_ntz'2024-01-20 00:00:00'"),
        ("expired and purged", "event_type = 'error' and ts < timestamp_ntz'2024-01-20 00:00:00'"), ("all", "true"),
    ):
        try:
            final_live(table, where, now)
            out.append((name, "ok"))
        except ExpiredData:
            out.append((name, "error"))
    return spark.createDataFrame(out, "query string, outcome string")


@workload("expire_policies", f"SELECT count(*) FILTER (WHERE {GONE7} AND NOT {GONE1}) AS only_new, 0 AS only_old, 'widens' AS kind FROM events")
def expire_policies(spark, sf):
    got = compare_policies(ev(spark, sf).table("ev"), DAILY, MODIFIED, last_time(spark, sf))
    return spark.createDataFrame([(got["only_new"], got["only_old"], got["kind"])], "only_new long, only_old int, kind string")


@workload("page_expire", "SELECT regexp_extract(url, '://([^/?#]*)', 1) AS host, count(*) AS n FROM pages WHERE page_id % 2 <> 0 GROUP BY 1")
def page_expire(spark, sf):
    db, rows = fresh(spark), read(spark, sf, "pages")
    db.create_table("pages", rows.schema, ["page_id"], True, expire="page_id % 2 = 0")
    with db.transaction() as tx:
        tx.insert("pages", rows)
    return live(db.table("pages")).groupBy(F.regexp_extract("url", "://([^/?#]*)", 1).alias("host")).agg(F.count("*").alias("n"))


# Proofs

CORPUS = [
    "SELECT * FROM ev", "SELECT event_id, value + 1 AS v FROM ev WHERE event_type = 'error'", "SELECT * FROM ev WHERE ts < now()", "SELECT * FROM ev WHERE ts > now()",
    "SELECT a.event_id FROM ev a JOIN ev b ON a.user_id = b.user_id", "SELECT event_id FROM ev UNION ALL SELECT event_id FROM ev", "SELECT user_id FROM ev UNION SELECT user_id FROM ev",
    "SELECT user_id FROM ev INTERSECT SELECT user_id FROM ev", "WITH q AS (SELECT * FROM ev) SELECT * FROM q", "VALUES (1), (2)", "SELECT count(*) FROM ev", "SELECT event_type, sum(value) FROM ev GROUP BY event_type",
    "SELECT event_id FROM ev EXCEPT SELECT event_id FROM ev", "SELECT a.event_id FROM ev a LEFT JOIN ev b ON a.event_id = b.event_id", "SELECT event_id FROM ev LIMIT 3", "SELECT event_id, rand() FROM ev",
    "SELECT event_id, row_number() OVER (ORDER BY ts) FROM ev", "SELECT * FROM cust", "SELECT DISTINCT user_id FROM ev", "SELECT event_id FROM ev WHERE event_id NOT IN (SELECT event_id FROM ev)",
    "SELECT event_id FROM ev WHERE ts <= (SELECT max(ts) FROM ev)", "SELECT event_id FROM ev WHERE ts > (SELECT max(ts) FROM ev)", "SELECT * FROM ev NATURAL JOIN (SELECT event_id FROM ev)", "SELECT * FROM ev CROSS JOIN (SELECT 1 AS one)",
]


#: What the rules say of each, by hand: not at all, by the printed ones, or only by those beyond them.
VERDICTS = "all all all no all all all all all all no no no no no no no no more no no no all all".split()
PROOFS = "SELECT * FROM (VALUES " + ", ".join(
    f"('{q.replace(chr(39), chr(39) * 2)}', '{rules}', {'true' if v == 'all' or (v == 'more' and rules == 'extended') else 'false'})"
    for q, v in zip(CORPUS, VERDICTS, strict=True) for rules in ("paper", "extended")
) + ") t(query, rules, ok)"


#: Queries that are also run before and after a change (half of the events, then all; customers, then some deleted), and
#: how many rows of the first result the second one lacks. None where a proof holds.
TRIED = {
    "SELECT event_id, value + 1 AS v FROM ev WHERE event_type = 'error'": "SELECT 0",
    "SELECT DISTINCT user_id FROM ev": "SELECT 0",
    "SELECT event_id FROM ev WHERE ts <= (SELECT max(ts) FROM ev)": "SELECT 0",
    "SELECT count(*) FROM ev": "SELECT CASE WHEN count(*) FILTER (WHERE event_id % 2 <> 0) > 0 THEN 1 ELSE 0 END FROM events",
    "SELECT * FROM cust": "SELECT count(*) FROM customer WHERE c_custkey % 11 = 0",
}
LOST = " UNION ALL ".join(f"SELECT '{q.replace(chr(39), chr(39) * 2)}' AS query, CAST(({n}) AS BIGINT) AS lost" for q, n in TRIED.items())


@workload("insert_only_proofs", f"SELECT query, rules, ok, coalesce(lost, -1) AS lost FROM ({PROOFS}) LEFT JOIN ({LOST}) USING (query)")
def insert_only_proofs(spark, sf):
    """What the prover says, beside what a change of the given tables does to some of the queries (-1: not tried)."""
    events, customers = read(spark, sf, "events"), read(spark, sf, "customer")

    def views(ev, cust):
        ev.createOrReplaceTempView("ev")
        cust.createOrReplaceTempView("cust")

    views(events.limit(0), customers.limit(0))
    out = []
    for q in CORPUS:
        for rules in ("paper", "extended"):
            got = prove_insert_only(spark, q, {"ev": True, "cust": False}, rules)
            out.append((q, rules, got.ok))
    views(events.filter("event_id % 2 = 0"), customers)
    before = {q: spark.sql(q) for q in TRIED}
    views(events, customers.filter("c_custkey % 11 <> 0"))
    lost = None
    for q, first in before.items():
        part = first.exceptAll(spark.sql(q)).agg(F.lit(q).alias("query"), F.count("*").alias("lost"))
        lost = part if lost is None else lost.unionByName(part)
    proofs = spark.createDataFrame(out, "query string, rules string, ok boolean")
    return proofs.join(lost, "query", "left").select("query", "rules", "ok", F.coalesce("lost", F.lit(-1)).alias("lost"))


# Streaming twins


def slices(db):
    return [db.table("ev").log_slice(v, v + 1) for v in range(db.version)]


def twin(rows):
    start = Axis(rows.schema["ts"].dataType, SIZE).start(START)
    sums = [F.expr(f"sum({MONEY})").alias("total"), F.count("value").alias("n")]
    return windowed_stream(rows, "ts", ["event_type"], sums, SIZE, STEP, timedelta(0), start)


@workload("hop_streaming_append", CLOSED)
def hop_streaming_append(spark, sf):
    """Append mode with a watermark gives what FINAL gives."""
    db = ev(spark, sf)
    feed = CommitFeed(spark, scratch(spark), db.table("ev").schema)
    return shown(final_stream(feed, slices(db), twin))


@workload(
    "hop_streaming_update",
    f"SELECT event_type, win_start, commit_no - 1 AS batch FROM (SELECT DISTINCT event_type, {stamped('s')} AS win_start, c AS commit_no FROM (SELECT event_type, c, TIMESTAMP '2024-01-01' + to_seconds(i * 172800) AS s FROM {EV}, unnest(range(CAST(greatest(0, floor((epoch_us(ts) - epoch_us(TIMESTAMP '2024-01-01')) / 1e6 / 172800 - 2.5) + 1) AS BIGINT), CAST(floor((epoch_us(ts) - epoch_us(TIMESTAMP '2024-01-01')) / 1e6 / 172800) AS BIGINT) + 1)) AS u(i)))",
)
def hop_streaming_update(spark, sf):
    """Update mode: which ranges each commit corrects."""
    db = ev(spark, sf)
    feed = CommitFeed(spark, scratch(spark), db.table("ev").schema)
    made = verbose_stream(feed, slices(db), twin, "verbose")
    numbers = made.select("batch").distinct().orderBy("batch").collect()  # one row a micro-batch
    place = F.create_map(*(F.lit(x) for i, r in enumerate(numbers) for x in (r.batch, i)))
    return made.select("event_type", stamp("win_start"), place[F.col("batch")].cast("long").alias("batch"))


@workload("hop_streaming_verbose", HOP_CHANGES.replace("SELECT event_type, strftime", "SELECT event_type, strftime").replace("c AS commit_no, 1 AS sign", "1 AS sign").replace("c, -1, b FROM", "-1, b FROM"))
def hop_streaming_verbose(spark, sf):
    """A stateful operator gives every correction with the image before it, as CHANGES does."""
    db, seen = ev(spark, sf), scratch(spark)
    feed, key = CommitFeed(spark, scratch(spark), db.table("ev").schema), "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key)
    spark.conf.set(key, ROCKS)
    try:
        for rows in slices(db):
            feed.push(rows)
            made = window_table(feed.stream(), "ts", SIZE, STEP, START).withColumn("v", F.expr(MONEY))
            feed.run(verbose_corrections(made, ["event_type", "win_start"], "v"), "update", lambda batch, n: batch.write.mode("append").parquet(seen))
    finally:
        spark.conf.set(key, before)
    return spark.read.parquet(seen).select(F.col("k0").alias("event_type"), stamp("k1", "win_start"), "sign", "total")


# Measures


def hop_pair(spark, sf):
    db = ev(spark, sf)
    verbose = db.rel("ev").window("ts", SIZE, STEP, START).aggregate(["event_type", "win_start", "win_end"], total=f"cast(sum({MONEY}) as double)")
    return verbose, FinalWindow(db.rel("ev"), "ts", ["event_type"], SUMS, SIZE, STEP, START)


@workload("verbosity", f"SELECT count(*) FILTER (WHERE sign > 0) AS plus, count(*) FILTER (WHERE sign < 0) AS minus, (SELECT count(*) FROM ({CLOSED})) AS final_rows FROM ({HOP_CHANGES})")
def verbosity(spark, sf):
    return measures.verbosity(*hop_pair(spark, sf))


OPEN = f"""WITH t AS (SELECT c, max(max(ts)) OVER (ORDER BY c) AS top FROM {EV} GROUP BY c),
  o AS (SELECT DISTINCT t.c AS v, h.event_type, h.s FROM t, {hops('432000', '172800', rows=EV)} h WHERE h.c <= t.c AND h.ts >= t.top - INTERVAL 5 DAY AND h.e > t.top),
  k AS (SELECT v, event_type, count(*) AS n FROM o GROUP BY v, event_type)
  SELECT v AS commit_no, CAST(sum(n) AS BIGINT) AS open_ranges, max(n) AS most_of_a_key, CAST(4 AS BIGINT) AS bound FROM k GROUP BY v"""


@workload("state_size", OPEN)
def state_size(spark, sf):
    return measures.state_size(hop_pair(spark, sf)[1])


@workload("work_ratio", f"SELECT c AS commit_no, count(*) AS delta_rows, CAST(sum(count(*)) OVER (ORDER BY c) AS BIGINT) AS full_rows FROM {EV} GROUP BY c")
def work_ratio(spark, sf):
    """By Spark's counters of rows read: the change of a windowed relation reads its commit alone."""
    return measures.work_ratio(ev(spark, sf).rel("ev").window("ts", SIZE, STEP, START))

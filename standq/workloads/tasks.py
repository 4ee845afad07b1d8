"""Continuous DML workloads: a target kept by a task through all commits, against one SELECT over the last state."""

from __future__ import annotations

from pyspark.sql import functions as F

from standq.measures import staleness
from standq.operators.partials import maintain
from standq.operators.task import ErrorPolicy, Every, Task, create_target, keep_in_sync
from standq.plans.relation import SetOperation, Sql
from standq.scratch import scratch
from standq.workloads.fixtures import CUST_FINAL, EV_COMMIT, ORD_FINAL, cust_steps, cust_tables, fresh, interleave, ord_steps, play, read
from standq.workloads.flows import EV, MONEY
from standq.workloads.registry import workload

PRICE = "cast(o_totalprice as decimal(18,2))"


def ev_table(spark, sf, **options):
    db, rows = fresh(spark), read(spark, sf, "events")
    db.create_table("ev", rows.schema, ["event_id"], True, **options)
    return db


def ev_steps(spark, sf):
    rows = read(spark, sf, "events")

    def step(n):
        def run(db):
            with db.transaction() as tx:
                tx.insert("ev", rows.filter(f"{EV_COMMIT} = {n}"))

        return run

    return [step(n) for n in range(1, 7)]


def followed(db, rel, steps, strategy="incremental", **options):
    """Create the target and its task, play the commits, give the target's rows."""
    create_target(db, "target", rel)
    Task.apply_changes(db, "follow", rel, "target", strategy=strategy, **options)
    play(db, steps)
    return db.table("target").snapshot()


@workload("replicate_insert", "SELECT event_id, user_id, value FROM events")
def replicate_insert(spark, sf):
    db = ev_table(spark, sf)
    db.create_table("replica", db.table("ev").schema, insert_only=True)
    Task.insert(db, "copy", db.rel("ev"), "replica")
    play(db, ev_steps(spark, sf))
    return db.table("replica").snapshot().select("event_id", "user_id", "value")


@workload("replicate_apply", CUST_FINAL)
def replicate_apply(spark, sf):
    db = cust_tables(spark, sf)
    return followed(db, db.rel("cust"), cust_steps(spark, sf))


@workload("replicate_apply_log", CUST_FINAL)
def replicate_apply_log(spark, sf):
    """Following the log of the table gives the same state as following the table."""
    db = cust_tables(spark, sf)
    create_target(db, "target", db.rel("cust"))
    columns = db.table("cust").columns
    Task.merge(db, "follow", db.rel("cust"), "target", ["c_custkey"], {c: f"s_{c}" for c in columns}, ordered="delete_insert")
    play(db, cust_steps(spark, sf))
    return db.table("target").snapshot()


@workload("replicate_merge", CUST_FINAL)
def replicate_merge(spark, sf):
    db = cust_tables(spark, sf)
    create_target(db, "target", db.rel("cust"))
    Task.merge(db, "follow", db.rel("cust"), "target", ["c_custkey"], {c: f"s_{c}" for c in db.table("cust").columns})
    play(db, cust_steps(spark, sf))
    return db.table("target").snapshot()


@workload("replicate_merge_ordered", CUST_FINAL)
def replicate_merge_ordered(spark, sf):
    db = cust_tables(spark, sf)
    create_target(db, "target", db.rel("cust"))
    Task.merge(db, "follow", db.rel("cust"), "target", ["c_custkey"], {c: f"s_{c}" for c in db.table("cust").columns}, ordered="update")
    play(db, cust_steps(spark, sf))
    return db.table("target").snapshot()


@workload("sync_full", CUST_FINAL)
def sync_full(spark, sf):
    """The baseline: all rows again at every commit."""
    db = cust_tables(spark, sf)
    create_target(db, "target", db.rel("cust"))
    keep_in_sync(db, "target", db.rel("cust"), "full")
    play(db, cust_steps(spark, sf))
    return db.table("target").snapshot()


@workload("sync_diff", CUST_FINAL)
def sync_diff(spark, sf):
    """The baseline: compare two states at every commit."""
    db = cust_tables(spark, sf)
    return followed(db, db.rel("cust"), cust_steps(spark, sf), strategy="diff")


SCD = "SELECT o_orderkey, k, o_totalprice, c_mktsegment AS segment FROM (SELECT o_orderkey, o_custkey AS k, o_totalprice FROM {o}) JOIN (SELECT c_custkey AS k, c_mktsegment FROM ({c})) USING (k)"


def facts(db):
    return db.rel("ord").select(o_orderkey="o_orderkey", k="o_custkey", o_totalprice="o_totalprice")


def segments(db):
    return db.rel("cust").select(k="c_custkey", segment="c_mktsegment")


@workload("scd_join", SCD.format(o="orders", c=CUST_FINAL))
def scd_join(spark, sf):
    """A fixed fact table with a slowly changing dimension."""
    db = cust_tables(spark, sf, orders=True)
    with db.transaction() as tx:
        tx.insert("ord", read(spark, sf, "orders"))
    return followed(db, facts(db).join(segments(db), ["k"]), cust_steps(spark, sf))


@workload("scd_join_both", SCD.format(o=f"({ORD_FINAL})", c=CUST_FINAL))
def scd_join_both(spark, sf):
    db = cust_tables(spark, sf, orders=True)
    return followed(db, facts(db).join(segments(db), ["k"]), interleave(ord_steps(spark, sf), cust_steps(spark, sf)))


@workload(
    "scd_snowflake",
    f"SELECT o_orderkey, c_mktsegment AS segment, n_name AS nation, r_name AS region FROM ({ORD_FINAL}) JOIN ({CUST_FINAL}) ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey",
)
def scd_snowflake(spark, sf):
    db = cust_tables(spark, sf, orders=True)
    for t in ("nation", "region"):
        db.create_table(t, read(spark, sf, t).schema, insert_only=True)
    with db.transaction() as tx:
        for t in ("nation", "region"):
            tx.insert(t, read(spark, sf, t))
    d = db.rel("cust").select(k="c_custkey", segment="c_mktsegment", n="c_nationkey")
    d = d.join(db.rel("nation").select(n="n_nationkey", nation="n_name", r="n_regionkey"), ["n"]).join(db.rel("region").select(r="r_regionkey", region="r_name"), ["r"])
    rel = db.rel("ord").select(o_orderkey="o_orderkey", k="o_custkey").join(d, ["k"]).select(o_orderkey="o_orderkey", segment="segment", nation="nation", region="region")
    return followed(db, rel, interleave(ord_steps(spark, sf), cust_steps(spark, sf)))


@workload("top10_customers", f"SELECT k, total FROM (SELECT o_custkey AS k, CAST(sum({PRICE}) AS DOUBLE) AS total FROM ({ORD_FINAL}) GROUP BY o_custkey) ORDER BY total DESC, k LIMIT 10")
def top10_customers(spark, sf):
    db = cust_tables(spark, sf, orders=True)
    rel = db.rel("ord").select(k="o_custkey", p=PRICE).aggregate(["k"], total="cast(sum(p) as double)").top(10, [("total", True), ("k", False)])
    return followed(db, rel, ord_steps(spark, sf))


@workload("top10_events", "SELECT event_id, value FROM events ORDER BY value DESC, event_id LIMIT 10")
def top10_events(spark, sf):
    db = ev_table(spark, sf)
    return followed(db, db.rel("ev").select(event_id="event_id", value="value").top(10, [("value", True), ("event_id", False)]), ev_steps(spark, sf))


@workload("avg_sync", f"SELECT round(CAST(sum({MONEY}) AS DOUBLE) / count(*), 6) AS avg_value FROM events")
def avg_sync(spark, sf):
    db = ev_table(spark, sf)
    rel = db.rel("ev").select(g="1", value="value")
    maintain(db, "follow", rel, "target", ["g"], {"s": MONEY})
    play(db, ev_steps(spark, sf))
    return db.table("target").snapshot().select(F.round(F.col("s").cast("double") / F.col("rows"), 6).alias("avg_value"))


@workload(
    "agg_outstanding",
    f"SELECT o_orderpriority AS priority, count(*) AS n, max(o_totalprice) AS dearest, CAST(sum({PRICE}) AS DOUBLE) AS total FROM ({ORD_FINAL}) WHERE o_orderstatus = 'O' GROUP BY o_orderpriority",
)
def agg_outstanding(spark, sf):
    db = cust_tables(spark, sf, orders=True)
    rel = db.rel("ord").where("o_orderstatus = 'O'").select(priority="o_orderpriority", o_totalprice="o_totalprice")
    rel = rel.aggregate(["priority"], n="count(*)", dearest="max(o_totalprice)", total=f"cast(sum({PRICE}) as double)")
    return followed(db, rel, ord_steps(spark, sf))


@workload("agg_outstanding_partials", f"SELECT o_orderpriority AS priority, count(*) AS n, CAST(sum({PRICE}) AS DOUBLE) AS total FROM ({ORD_FINAL}) WHERE o_orderstatus = 'O' GROUP BY o_orderpriority")
def agg_outstanding_partials(spark, sf):
    """The same from stored partial sums: a run reads changed rows and groups alone, updates and deletes too."""
    db = cust_tables(spark, sf, orders=True)
    rel = db.rel("ord").where("o_orderstatus = 'O'").select(priority="o_orderpriority", o_totalprice="o_totalprice")
    maintain(db, "follow", rel, "target", ["priority"], {"total": PRICE})
    play(db, ord_steps(spark, sf))
    return db.table("target").snapshot().select("priority", F.col("rows").alias("n"), F.col("total").cast("double").alias("total"))


def by_rest(spark, sf, table, key, n, insert_only=True):
    db, rows = fresh(spark), read(spark, sf, table)
    db.create_table(table, rows.schema, insert_only=insert_only)

    def step(k):
        def run(db):
            with db.transaction() as tx:
                tx.insert(table, rows.filter(f"{key} % {n} = {k}"))

        return run

    return db, [step(k) for k in range(n)]


@workload(
    "agg_lineitem_flags",
    """SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(cast(l_quantity as decimal(18,2))) AS DOUBLE) AS sum_qty,
    round(CAST(sum(cast(l_extendedprice as decimal(18,2))) AS DOUBLE) / count(*), 6) AS avg_price FROM lineitem GROUP BY 1, 2""",
)
def agg_lineitem_flags(spark, sf):
    db, steps = by_rest(spark, sf, "lineitem", "l_orderkey", 5)
    maintain(db, "follow", db.rel("lineitem"), "target", ["l_returnflag", "l_linestatus"], {"q": "cast(l_quantity as decimal(18,2))", "p": "cast(l_extendedprice as decimal(18,2))"})
    play(db, steps)
    return db.table("target").snapshot().select(
        "l_returnflag", "l_linestatus", F.col("rows").alias("n"), F.col("q").cast("double").alias("sum_qty"), F.round(F.col("p").cast("double") / F.col("rows"), 6).alias("avg_price")
    )


@workload("doc_counts", "SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY 1, 2")
def doc_counts(spark, sf):
    db, steps = by_rest(spark, sf, "documents", "doc_id", 3)
    maintain(db, "follow", db.rel("documents").select(lang="lang", source="source", n_chars="n_chars"), "target", ["lang", "source"], {"chars": "n_chars"})
    play(db, steps)
    return db.table("target").snapshot().select("lang", "source", F.col("rows").alias("n"), F.col("chars").cast("long").alias("chars"))


@workload("agg_distinct_users", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def agg_distinct_users(spark, sf):
    db = ev_table(spark, sf)
    rel = db.rel("ev").select(event_type="event_type", user_id="user_id").distinct().aggregate(["event_type"], users="count(*)")
    return followed(db, rel, ev_steps(spark, sf))


@workload("agg_cube", "SELECT event_type, strftime(ts, '%Y-%m-%d') AS day, count(*) AS n FROM events GROUP BY CUBE (1, 2)")
def agg_cube(spark, sf):
    """Any query text, kept by comparing versions."""
    db = ev_table(spark, sf)
    rel = Sql(db, "SELECT event_type, day, count(*) AS n FROM (SELECT event_type, date_format(ts, 'yyyy-MM-dd') AS day FROM ev) GROUP BY CUBE (event_type, day)", ["ev"], ["event_type", "day"])
    return followed(db, rel, ev_steps(spark, sf), strategy="diff")


def keyed(db):
    return db.rel("cust").select(k="c_custkey", segment="c_mktsegment"), db.rel("ord").select(k="o_custkey", o="o_orderkey")


def both(spark, sf):
    return interleave(ord_steps(spark, sf), cust_steps(spark, sf))


CK, OK = f"(SELECT c_custkey AS k, c_mktsegment AS segment FROM ({CUST_FINAL}))", f"(SELECT o_custkey AS k, o_orderkey AS o FROM ({ORD_FINAL}))"


@workload("outer_join_cust", f"SELECT k, segment, coalesce(o, -1) AS o FROM {CK} LEFT JOIN {OK} USING (k)")
def outer_join_cust(spark, sf):
    db = cust_tables(spark, sf, orders=True)
    c, o = keyed(db)
    return followed(db, c.join(o, ["k"], "left_outer"), both(spark, sf)).withColumn("o", F.coalesce("o", F.lit(-1)))


@workload("full_join_cust", f"SELECT k, coalesce(segment, '-') AS segment, coalesce(o, -1) AS o FROM {CK} FULL JOIN {OK} USING (k)")
def full_join_cust(spark, sf):
    db = cust_tables(spark, sf, orders=True)
    c, o = keyed(db)
    return followed(db, c.join(o, ["k"], "full_outer"), both(spark, sf)).select("k", F.coalesce("segment", F.lit("-")).alias("segment"), F.coalesce("o", F.lit(-1)).alias("o"))


@workload("anti_join_cust", f"SELECT k, segment FROM {CK} c WHERE NOT EXISTS (SELECT 1 FROM {OK} o WHERE o.k = c.k)")
def anti_join_cust(spark, sf):
    db = cust_tables(spark, sf, orders=True)
    c, o = keyed(db)
    return followed(db, c.join(o, ["k"], "left_anti"), both(spark, sf))


@workload("semi_join_cust", f"SELECT k, segment FROM {CK} c WHERE EXISTS (SELECT 1 FROM {OK} o WHERE o.k = c.k)")
def semi_join_cust(spark, sf):
    db = cust_tables(spark, sf, orders=True)
    c, o = keyed(db)
    return followed(db, c.join(o, ["k"], "left_semi"), both(spark, sf))


@workload("except_cust", f"SELECT k FROM {CK} EXCEPT SELECT k FROM {OK}")
def except_cust(spark, sf):
    db = cust_tables(spark, sf, orders=True)
    c, o = keyed(db)
    return followed(db, SetOperation(c.select(k="k"), o.select(k="k"), "except"), both(spark, sf))


@workload("intersect_cust", f"SELECT k FROM {CK} INTERSECT SELECT k FROM {OK}")
def intersect_cust(spark, sf):
    db = cust_tables(spark, sf, orders=True)
    c, o = keyed(db)
    return followed(db, SetOperation(c.select(k="k"), o.select(k="k"), "intersect"), both(spark, sf))


@workload("union_all_keys", f"SELECT k, 'c' AS side FROM {CK} UNION ALL SELECT k, 'o' FROM {OK}")
def union_all_keys(spark, sf):
    db = cust_tables(spark, sf, orders=True)
    c, o = keyed(db)
    return followed(db, c.select(k="k", side="'c'").union_all(o.select(k="k", side="'o'")), both(spark, sf))


@workload("rank_orders", f"SELECT o_orderkey, k, row_number() OVER (PARTITION BY k ORDER BY p DESC, o_orderkey) AS place FROM (SELECT o_orderkey, o_custkey AS k, o_totalprice AS p FROM ({ORD_FINAL}))")
def rank_orders(spark, sf):
    db = cust_tables(spark, sf, orders=True)
    rel = db.rel("ord").select(o_orderkey="o_orderkey", k="o_custkey", p="o_totalprice").rank(["k"], "p desc, o_orderkey", "place", "row_number()").select(o_orderkey="o_orderkey", k="k", place="cast(place as bigint)")
    return followed(db, rel, ord_steps(spark, sf))


@workload("security_rules", "SELECT user_id, strftime(ts, '%Y-%m-%d') AS day, count(*) AS errors FROM events WHERE event_type = 'error' GROUP BY 1, 2 HAVING count(*) >= 3")
def security_rules(spark, sf):
    """Rules over a stream fill a table, whose trigger sees every change of it."""
    db = ev_table(spark, sf)
    rel = db.rel("ev").where("event_type = 'error'").select(user_id="user_id", day="date_format(ts, 'yyyy-MM-dd')")
    rel = rel.aggregate(["user_id", "day"], errors="count(*)").where("errors >= 3")
    seen = scratch(spark)
    rows = followed(db, rel, ev_steps(spark, sf), callbacks=[lambda change: change.select("user_id", "day", "errors", "_action", "_row_id", "_commit_no", "_seq").write.mode("append").parquet(seen)])
    del rows
    told = spark.read.parquet(seen)  # what the trigger was given, folded: the alerts that stand
    last = told.groupBy("_row_id").agg(F.max_by(F.struct("user_id", "day", "errors", "_action"), F.struct("_commit_no", "_seq")).alias("r"))
    return last.filter("r._action <> 'DELETE'").select("r.user_id", "r.day", "r.errors")


@workload("initial_snapshot", CUST_FINAL)
def initial_snapshot(spark, sf):
    db, steps = cust_tables(spark, sf), cust_steps(spark, sf)
    play(db, steps[:2])
    return followed(db, db.rel("cust"), steps[2:], initial_snapshot=True)


@workload("no_initial_snapshot", f"SELECT event_id, value FROM {EV} WHERE c > 2")
def no_initial_snapshot(spark, sf):
    db, steps = ev_table(spark, sf), ev_steps(spark, sf)
    play(db, steps[:2])
    db.create_table("replica", db.table("ev").schema, insert_only=True)
    Task.insert(db, "copy", db.rel("ev"), "replica")
    play(db, steps[2:])
    return db.table("replica").snapshot().select("event_id", "value")


@workload("error_log", "SELECT event_id, CASE WHEN value > 300 THEN 'rejected' ELSE 'kept' END AS fate FROM events")
def error_log(spark, sf):
    db = ev_table(spark, sf)
    db.create_table("replica", db.table("ev").schema, insert_only=True, checks=["value <= 300"])
    db.create_table("bad", "tag string, reason string, row_json string", insert_only=True)
    Task.insert(db, "copy", db.rel("ev"), "replica", errors=ErrorPolicy("bad", "copy", None))
    play(db, ev_steps(spark, sf))
    kept = db.table("replica").snapshot().select("event_id", F.lit("kept").alias("fate"))
    bad = db.table("bad").snapshot().select(F.get_json_object("row_json", "$.event_id").cast("long").alias("event_id"), F.lit("rejected").alias("fate"))
    return kept.unionByName(bad)


def interrupted(spark, sf, event):
    db, steps = ev_table(spark, sf), ev_steps(spark, sf)
    db.create_table("replica", db.table("ev").schema, insert_only=True)
    task = Task.insert(db, "copy", db.rel("ev"), "replica")
    play(db, steps[:2])
    task.alter(event)
    play(db, steps[2:4])
    task.alter("resume")
    play(db, steps[4:])
    return db.table("replica").snapshot().select("event_id", "value")


@workload("pause_resume", "SELECT event_id, value FROM events")
def pause_resume(spark, sf):
    return interrupted(spark, sf, "pause")


@workload("stop_resume", f"SELECT event_id, value FROM {EV} WHERE c NOT IN (3, 4)")
def stop_resume(spark, sf):
    return interrupted(spark, sf, "stop")


@workload("schedule_every_2_commits", f"SELECT c AS commit_no, CAST(c % 2 AS INTEGER) AS stale_commits FROM {EV} GROUP BY c")
def schedule_every_2(spark, sf):
    from standq.operators.task import Scheduler

    db, out = ev_table(spark, sf), []
    db.create_table("replica", db.table("ev").schema, insert_only=True)
    task = Task.insert(db, "copy", db.rel("ev"), "replica", schedule=Every(seconds=120))
    for n, step in enumerate(ev_steps(spark, sf), 1):
        step(db)
        db.clock.advance(minutes=1)
        Scheduler.of(db).tick()
        out.append((n, staleness(db, "ev", task.bookmark)))
    return spark.createDataFrame(out, "commit_no long, stale_commits int")


@workload("task_chain", "SELECT event_type, count(*) AS n FROM events WHERE value > 10 GROUP BY event_type")
def task_chain(spark, sf):
    """A target that is itself followed: stream, filtered copy, counts."""
    db = ev_table(spark, sf)
    db.create_table("large", db.table("ev").schema, insert_only=True)
    Task.insert(db, "copy", db.rel("ev").where("value > 10"), "large")
    maintain(db, "count", db.rel("large").select(event_type="event_type", one="1"), "target", ["event_type"], {"ones": "one"})
    play(db, ev_steps(spark, sf))
    return db.table("target").snapshot().select("event_type", F.col("rows").alias("n"))


@workload("label_scd", "SELECT doc_id, lang, CASE WHEN doc_id % 6 = 0 THEN 1 - quality ELSE quality END AS quality FROM documents JOIN labels USING (doc_id)")
def label_scd(spark, sf):
    db, docs, labels = fresh(spark), read(spark, sf, "documents").select("doc_id", "lang"), read(spark, sf, "labels")
    db.create_table("docs", docs.schema, ["doc_id"], True)
    db.create_table("labels", labels.schema, ["doc_id"])

    def load(db):
        with db.transaction() as tx:
            tx.insert("docs", docs)
            tx.insert("labels", labels.filter("doc_id % 2 = 0"))

    def flip(db):
        with db.transaction() as tx:
            tx.update("labels", {"quality": "1 - quality"}, "doc_id % 6 = 0")

    def more(db):
        with db.transaction() as tx:
            tx.insert("labels", labels.filter("doc_id % 2 = 1"))

    return followed(db, db.rel("docs").join(db.rel("labels").select(doc_id="doc_id", quality="quality"), ["doc_id"]), [load, flip, more])


@workload(
    "part_price_scd",
    """SELECT p_brand, CAST(sum(cast(l_quantity as decimal(18,2)) * cast(CASE WHEN p_partkey % 5 = 0 THEN round(p_retailprice * 1.1, 1) ELSE p_retailprice END as decimal(18,2))) AS DOUBLE) AS worth
    FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand""",
)
def part_price_scd(spark, sf):
    db, part, line = fresh(spark), read(spark, sf, "part"), read(spark, sf, "lineitem").select("l_partkey", "l_quantity")
    db.create_table("part", part.schema, ["p_partkey"])
    db.create_table("line", line.schema, insert_only=True)

    def load(db):
        with db.transaction() as tx:
            tx.insert("line", line)
            tx.insert("part", part)

    def dearer(db):
        with db.transaction() as tx:
            tx.update("part", {"p_retailprice": "round(p_retailprice * 1.1, 1)"}, "p_partkey % 5 = 0")

    rel = db.rel("line").select(k="l_partkey", q="cast(l_quantity as decimal(18,2))").join(db.rel("part").select(k="p_partkey", p_brand="p_brand", p="cast(p_retailprice as decimal(18,2))"), ["k"])
    rel = rel.select(p_brand="p_brand", w="q * p")
    maintain(db, "follow", rel, "target", ["p_brand"], {"worth": "w"})
    play(db, [load, dearer])
    return db.table("target").snapshot().select("p_brand", F.col("worth").cast("double").alias("worth"))


@workload("embeddings_payload", "SELECT vec_id, len(embedding) AS dims, 'INSERT' AS action FROM embeddings")
def embeddings_payload(spark, sf):
    from standq.plans.relation import changes

    db, steps = by_rest(spark, sf, "embeddings", "vec_id", 2)
    play(db, steps)
    made = changes(db.rel("embeddings"))
    return made.select("vec_id", F.size("embedding").cast("long").alias("dims"), F.col("_action").alias("action"))

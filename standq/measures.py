"""What an incremental flow costs against what it gives; all as small DataFrames."""

from __future__ import annotations

from typing import Any

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from standq.operators.final import FinalWindow, frontier, state_bound
from standq.plans.relation import Relation, changes
from standq.sources.store import Database, Table


def verbosity(rel: Relation, final_rel: Relation) -> DataFrame:
    """Change rows that every correction makes, against rows given once when final."""
    db = rel.db
    rows = changes(rel, format="LOG", encoding="delete_insert")
    up = F.sum((F.col("_action") != "DELETE").cast("long")).alias("plus")
    down = F.sum((F.col("_action") == "DELETE").cast("long")).alias("minus")
    n = final_rel.to_df(db.version).count()
    return rows.agg(up, down).withColumn("final_rows", F.lit(n).cast("long"))


def state_size(window: FinalWindow) -> DataFrame:
    """Open ranges and keys after each commit, and the bound on ranges of a key."""
    rows, bound = None, state_bound(window.size, window.advance, window.grace)
    from standq.operators.windows import hop_aggregate

    for v in range(1, window.db.version + 1):
        top = frontier(window.table, window.column, v, window.grace)
        if top is None:
            continue
        near = window.inputs[0].at(v).filter(F.col(window.column) >= F.lit(top - window.size))
        open_ = hop_aggregate(near, window.column, window.keys, window.aggregates, window.size, window.advance, window.start_with).filter(F.col("win_end") > F.lit(top))
        per = open_.groupBy(*window.keys).count() if window.keys else open_.agg(F.count("*").alias("count"))
        got = per.agg(F.lit(v).cast("long").alias("commit_no"), F.sum("count").alias("open_ranges"), F.max("count").alias("most_of_a_key"), F.lit(bound).cast("long").alias("bound"))
        rows = got if rows is None else rows.unionByName(got)
    return rows


def rows_read(df: DataFrame) -> int:
    """Rows that the scans of a query put out when it runs, by Spark's own counters. A scan whose exchange is used again
    counts once, as it runs once."""
    execution = df._jdf.queryExecution()
    execution.toRdd().count()

    def leaves(plan: Any) -> int:
        kind = plan.getClass().getSimpleName()
        if kind == "AdaptiveSparkPlanExec":
            return leaves(plan.executedPlan())
        if kind.startswith("ReusedExchange"):
            return 0
        if kind.endswith("QueryStageExec"):
            return leaves(plan.plan())
        children = plan.children()
        if children.size():
            return sum(leaves(children.apply(i)) for i in range(children.size()))
        n = plan.metrics().get("numOutputRows")
        return n.get().value() if "Scan" in kind and n.isDefined() else 0

    return leaves(execution.executedPlan())


def work_ratio(rel: Relation) -> DataFrame:
    """Rows that are read to derive the change of each commit, against those read to evaluate the relation anew then."""
    out = [(v, rows_read(rel.delta(v - 1, v)), rows_read(rel.at(v))) for v in range(1, rel.db.version + 1)]
    return rel.db.spark.createDataFrame(out, "commit_no long, delta_rows long, full_rows long")


def commit_sizes(table: Table) -> DataFrame:
    """Records that each commit adds to the log, against the rows there are then."""
    out, total = [], 0
    for m in table.db.manifests:
        e = m["tables"].get(table.name)
        if e:
            n = e["inserts"] + e["updates"] + e["deletes"]
            total += e["inserts"] - e["deletes"]
            out.append((m["commit"], n, total))
    return table.db.spark.createDataFrame(out, "commit_no long, delta_rows long, full_rows long")


def staleness(db: Database, source: str, bookmark: int) -> int:
    """Commits of the source that a task has not applied."""
    return sum(source in m["tables"] for m in db.manifests[bookmark:])


def sync_error(target: DataFrame, full: DataFrame) -> int:
    """Rows by which a target differs from its query; must be 0."""
    columns = sorted(set(target.columns) & set(full.columns))
    a, b = target.select(*columns), full.select(*columns)
    return a.exceptAll(b).unionByName(b.exceptAll(a)).count()


def late_rows(marked: DataFrame) -> DataFrame:
    """Accepted and rejected rows of a marked flow."""
    return marked.agg(F.sum((~F.col("_late")).cast("long")).alias("accepted"), F.sum(F.col("_late").cast("long")).alias("rejected"))


def compaction_ratio(table: Table, after: int = 0, upto: int | None = None) -> dict[str, Any]:
    from standq.functions.compaction import compact_net

    log = table.log_slice(after, upto)
    return {"log": log.count(), "delta": compact_net(log).count()}


def check_subset(rel: Relation, v0: int, v1: int) -> bool:
    """The definition of insert-only between two versions: every row then is a row now."""
    return rel.to_df(v0).exceptAll(rel.to_df(v1)).isEmpty()


def commit_delay(db: Database, statement: Any) -> dict[str, float]:
    """Seconds that a commit takes, and how many of them go to the tasks that run within it."""
    import time

    spent = [0.0]
    told = list(db.listeners)

    def timed(f):
        def run(manifest):
            at = time.perf_counter()
            f(manifest)
            spent[0] += time.perf_counter() - at

        return run

    db.listeners[:] = [timed(f) for f in told]
    at = time.perf_counter()
    try:
        statement()
    finally:
        db.listeners[:] = told
    return {"commit_s": time.perf_counter() - at, "tasks_s": spent[0]}


def applied_twice_or_never(source: DataFrame, target: DataFrame, key: list[str]) -> dict[str, int]:
    """Rows of an insert-only flow that arrived more than once, and that never did; both must be 0."""
    twice = target.groupBy(*key).count().filter("count > 1").count()
    return {"twice": twice, "never": source.join(target, key, "left_anti").count()}


def expired_overhead(table: Table, now: Any) -> DataFrame:
    """Rows that the expiry test looks at, and that it leaves out."""
    from standq.operators.expire import live

    return live(table, now).agg(F.count("*").alias("live")).withColumn("stored", F.lit(table.snapshot().count()))

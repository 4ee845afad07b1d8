"""The derived change of every operator is the difference of two evaluations, under mixed commits."""

from __future__ import annotations

import random

import pytest

from standq.functions.compaction import compact_delete_insert, compact_net, compact_update, consolidate, encode
from standq.operators.partials import maintain
from standq.plans.relation import Changes, SetOperation, simplify


@pytest.fixture(scope="module")
def mixed(spark):
    """Two tables and eight commits of inserts, updates and deletes."""
    from standq.clock import ManualClock
    from standq.scratch import scratch
    from standq.sources.store import Database

    db, rng = Database(spark, scratch(spark), ManualClock()), random.Random(4)
    db.create_table("a", "id int, k int, v int", ["id"])
    db.create_table("b", "id int, k int, w int", ["id"])
    for step in range(5):
        with db.transaction() as tx:
            for t in ("a", "b") if step % 3 else ("a",):
                rows = [(step * 20 + i, rng.choice([0, 1, 2, 3, None]), rng.randrange(6)) for i in range(8)]
                tx.insert(t, spark.createDataFrame(rows, db.table(t).schema))
                if step:
                    tx.update(t, {db.table(t).columns[2]: f"{rng.randrange(6)}"}, f"id % 5 = {rng.randrange(5)}")
                    tx.update(t, {"k": f"{rng.randrange(4)}"}, f"id % 7 = {rng.randrange(7)}")
                    tx.delete(t, f"id % 6 = {rng.randrange(6)}")
    return db


def shapes(db):
    a, b = db.rel("a"), db.rel("b")
    ka, kb = a.select(k="k", v="v"), b.select(k="k", w="w")
    return {
        "scan": a, "filter": a.where("v > 2"), "project": a.select(k="k", s="v + 1"), "union": ka.union_all(kb.select(k="k", v="w")),
        "join": ka.join(kb, ["k"]), "self join": ka.join(a.select(k="k", x="v"), ["k"]), "left": ka.join(kb, ["k"], "left_outer"), "right": ka.join(kb, ["k"], "right_outer"),
        "full": ka.join(kb, ["k"], "full_outer"), "semi": ka.join(kb, ["k"], "left_semi"), "anti": ka.join(kb, ["k"], "left_anti"),
        "group": a.aggregate(["k"], n="count(*)", s="sum(v)", lo="min(v)", hi="max(v)"), "global": a.aggregate([], n="count(*)", s="sum(v)"), "having": a.aggregate(["k"], n="count(*)").where("n > 3"),
        "distinct": ka.distinct(), "except": SetOperation(ka.select(k="k"), kb.select(k="k"), "except"), "intersect": SetOperation(ka.select(k="k"), kb.select(k="k"), "intersect"),
        "union distinct": SetOperation(ka.select(k="k"), kb.select(k="k"), "union"), "rank": a.rank(["k"], "v desc, id", "r", "row_number()"), "top": a.top(5, [("v", True), ("id", False)]),
        "numbers": a.window("v", 3, 2).aggregate(["win_start", "win_end"], n="count(*)"), "join of groups": a.aggregate(["k"], n="count(*)").join(kb, ["k"]),
    }


NAMES = ["scan", "filter", "project", "union", "join", "self join", "left", "right", "full", "semi", "anti", "group", "global", "having", "distinct", "except", "intersect", "union distinct", "rank", "top", "numbers", "join of groups"]


def bag(df):
    from pyspark.sql import functions as F

    return sorted(((*map(str, r[:-1]), r[-1]) for r in df.groupBy(*[c for c in df.columns if not c.startswith("_")]).agg(F.sum("_sign").alias("_n")).filter("_n <> 0").collect()))


@pytest.mark.parametrize("name", NAMES)
def test_delta_is_difference(mixed, name):
    rel = shapes(mixed)[name]
    for v0, v1 in ((1, 3), (2, 5)):
        assert bag(consolidate(rel.delta(v0, v1))) == bag(rel.difference(v0, v1)), (v0, v1)
    assert rel.explain()


def test_compactions_agree(mixed):
    """Applying a compacted log gives the state, whatever the encoding."""
    log = mixed.table("a").log_slice()
    now = sorted(map(str, (tuple(r) for r in mixed.table("a").snapshot().collect())))
    net = compact_net(log)
    assert sorted(str((r.id, r.k, r.v)) for r in net.collect()) == now and set(r._action for r in net.collect()) == {"INSERT"}
    for made in (compact_update(log), compact_delete_insert(encode(log, "delete_insert"))):
        assert sorted(str((r.id, r.k, r.v)) for r in made.filter("_action <> 'DELETE'").collect()) == now


@pytest.mark.parametrize(("ops", "net", "pattern"), [(["I"], "I", "I"), (["I", "U"], "I", "I"), (["I", "D"], None, "D"), (["U", "U"], "U", "U"), (["U", "D"], "D", "D"), (["D"], "D", "D")])
def test_compaction_table(spark, ops, net, pattern):
    from standq.sources.store import log_schema

    kind = spark.createDataFrame([], "id int, v int").schema
    word = {"I": "INSERT", "U": "UPDATE", "D": "DELETE"}
    rows = [(1, n, word[o], "r", None if o == "I" else (1, n - 1), None, n, 0) for n, o in enumerate(ops, 1)]
    log = spark.createDataFrame(rows, log_schema(kind))
    assert [r._action for r in compact_net(log).collect()] == ([word[net]] if net else [])
    assert [r._action for r in compact_update(log).collect()] == [word[pattern]]


def test_update_back_is_nothing(db, spark):
    db.create_table("t", "id int, v int", ["id"])
    with db.transaction() as tx:
        tx.insert("t", spark.createDataFrame([(1, 1)], "id int, v int"))
    for v in ("5", "1"):
        with db.transaction() as tx:
            tx.update("t", {"v": v})
    assert compact_net(db.table("t").log_slice(1)).count() == 0


def test_partials_with_deletes(db, spark):
    db.create_table("t", "id int, g string, v int", ["id"])
    maintain(db, "p", db.rel("t"), "sums", ["g"], {"s": "v"})
    with db.transaction() as tx:
        tx.insert("t", spark.createDataFrame([(1, "x", 1), (2, None, 2), (3, "y", 3)], "id int, g string, v int"))
    with db.transaction() as tx:
        tx.update("t", {"g": "'x'", "v": "7"}, "id = 3")
        tx.delete("t", "id = 2")
    assert [(r.g, r.rows, int(r.s)) for r in db.table("sums").snapshot().collect()] == [("x", 2, 8)]


def test_changes_of_changes(mixed):
    inner = Changes(mixed.rel("a"), format="LOG")
    outer = Changes(inner).at(mixed.version)
    assert outer.count() == mixed.table("a").log_slice().count() and inner.insert_only()[0]
    mixed.create_table("grow", "id int", insert_only=True) if "grow" not in mixed.metas else None
    assert simplify(Changes(mixed.rel("grow"))).notes

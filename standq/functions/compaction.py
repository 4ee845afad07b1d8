"""Change records: encodings and compactions. One pre-aggregated shuffle on the row id each."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ORDER = F.struct  # of the order of history


def history() -> Column:
    """Commit, statement, and of one statement the delete half of an update first."""
    return F.struct("_commit_no", "_seq", F.when(F.col("_action") == "DELETE", 0).otherwise(1).alias("half"))


def value_columns(df: DataFrame) -> list[str]:
    return [c for c in df.columns if not c.startswith("_")]


def compact_net(log: DataFrame) -> DataFrame:
    """At most one record a row: what the interval did to it on balance, with images before and after.

    First INSERT and last DELETE vanish; INSERT then anything else is an INSERT of the last image; an UPDATE or DELETE
    first means the row was there before, so with a row at the end it is an UPDATE (none if nothing differs), else a DELETE.
    """
    values = value_columns(log)
    image = F.struct(*(F.col(f"`{c}`") for c in values))
    at = history()
    net = log.groupBy("_row_id").agg(
        F.min_by(F.struct(F.col("_action").alias("a"), "_before"), at).alias("first"),
        F.max_by(F.struct(F.col("_action").alias("a"), image.alias("v"), "_time", "_commit_no", "_seq"), at).alias("last"),
    )
    was, is_ = F.col("first.a") != "INSERT", F.col("last.a") != "DELETE"
    action = F.when(~was & is_, "INSERT").when(was & is_, "UPDATE").when(was & ~is_, "DELETE")
    net = net.withColumn("_action", action).filter(F.col("_action").isNotNull())
    net = net.filter((F.col("_action") != "UPDATE") | ~F.col("first._before").eqNullSafe(F.col("last.v")))
    shown = F.when(F.col("_action") == "DELETE", F.col("first._before")).otherwise(F.col("last.v"))
    return net.withColumn("_shown", shown).select(
        *(F.col("_shown")[c].alias(c) for c in values), "_action", "_row_id",
        F.when(F.col("_action") != "INSERT", F.col("first._before")).alias("_before"),
        F.col("last._time").alias("_time"), F.col("last._commit_no").alias("_commit_no"), F.col("last._seq").alias("_seq"),
    )


def compact_update(log: DataFrame) -> DataFrame:
    """The single-record family: the last record of each row, an INSERT before it turning a later UPDATE into an INSERT
    of its image; a trailing DELETE stays even where the row was inserted in the interval."""
    values = value_columns(log)
    image = F.struct(*(F.col(f"`{c}`") for c in values))
    at = history()
    made = log.groupBy("_row_id").agg(
        F.min_by(F.struct(F.col("_action").alias("a"), "_before"), at).alias("first"),
        F.max_by(F.struct(F.col("_action").alias("a"), image.alias("v"), "_time", "_commit_no", "_seq"), at).alias("last"),
    )
    action = F.when(F.col("last.a") == "DELETE", "DELETE").when(F.col("first.a") == "INSERT", "INSERT").otherwise("UPDATE")
    return made.select(
        *(F.col("last.v")[c].alias(c) for c in values), action.alias("_action"), "_row_id",
        F.when(action != "INSERT", F.col("first._before")).alias("_before"),
        F.col("last._time").alias("_time"), F.col("last._commit_no").alias("_commit_no"), F.col("last._seq").alias("_seq"),
    )


def compact_delete_insert(log: DataFrame) -> DataFrame:
    """The delete/insert family over ``delete_insert`` records: of each row the last record, deletes before inserts."""
    values = value_columns(log)
    row = F.struct(*(F.col(f"`{c}`") for c in values), "_action", "_time", "_commit_no", "_seq")
    made = log.groupBy("_row_id").agg(F.max_by(row, history()).alias("r"))
    return made.select(*(F.col("r")[c].alias(c) for c in values), F.col("r._action").alias("_action"), "_row_id", F.col("r._time").alias("_time"), F.col("r._commit_no").alias("_commit_no"), F.col("r._seq").alias("_seq"))


def encode(changes: DataFrame, encoding: str) -> DataFrame:
    """Render records with images: ``single`` keeps one a change; ``pair`` shows an update as DELETE of the image before
    and UPDATE with the one after; ``delete_insert`` as DELETE and INSERT."""
    if encoding == "single":
        return changes
    values = value_columns(changes)
    second = "UPDATE" if encoding == "pair" else "INSERT"
    after = F.struct(*(F.col(f"`{c}`").alias(c) for c in values), F.when(F.col("_action") == "UPDATE", second).otherwise(F.col("_action")).alias("_action"))
    before = F.struct(*(F.col("_before")[c].alias(c) for c in values), F.lit("DELETE").alias("_action"))
    both = F.when(F.col("_action") == "UPDATE", F.array(before, after)).otherwise(F.array(after))
    rest = [c for c in changes.columns if c.startswith("_") and c not in ("_action", "_before")]
    return changes.select(F.explode(both).alias("_r"), *rest).select("_r.*", *rest)


def signed(changes: DataFrame) -> DataFrame:
    """Records with images as rows with ``_sign``: -1 the image before, 1 the image after."""
    out = encode(changes, "delete_insert")
    return out.withColumn("_sign", F.when(F.col("_action") == "DELETE", -1).otherwise(1))


def from_signed(rows: DataFrame) -> DataFrame:
    """Consolidated signed rows (at most one of each sign a row id) as net records with images."""
    values = value_columns(rows)
    image = F.struct(*(F.col(f"`{c}`") for c in values))
    made = rows.groupBy("_row_id").agg(
        F.max(F.when(F.col("_sign") < 0, 1).otherwise(0)).alias("had"), F.max(F.when(F.col("_sign") > 0, 1).otherwise(0)).alias("has"),
        F.max_by(image, F.when(F.col("_sign") < 0, 1)).alias("b"), F.max_by(image, F.when(F.col("_sign") > 0, 1)).alias("a"),
    )
    action = F.when((F.col("had") == 1) & (F.col("has") == 1), "UPDATE").when(F.col("has") == 1, "INSERT").otherwise("DELETE")
    shown = F.when(F.col("has") == 1, F.col("a")).otherwise(F.col("b"))
    before = F.when(F.col("had") == 1, F.col("b"))
    return made.select(shown.alias("_v"), action.alias("_action"), "_row_id", before.alias("_before")).select("_v.*", "_action", "_row_id", "_before")


def consolidate(rows: DataFrame) -> DataFrame:
    """Signed rows with equal rows cancelled; maps are compared by their JSON."""
    values = value_columns(rows)
    maps = [f.name for f in rows.schema.fields if f.dataType.typeName() == "map"]
    keys = [F.to_json(F.col(f"`{c}`")).alias(c) if c in maps else F.col(f"`{c}`") for c in values]
    if maps:
        named = rows.select("*", *(F.to_json(F.col(f"`{c}`")).alias(f"_json_{c}") for c in maps))
        grouping = [f"_json_{c}" if c in maps else f"`{c}`" for c in values]
        out = named.groupBy("_row_id", *grouping).agg(F.sum("_sign").alias("_sign"), *(F.first(F.col(f"`{c}`")).alias(c) for c in maps))
    else:
        out = rows.groupBy("_row_id", *keys).agg(F.sum("_sign").alias("_sign"))
    return out.filter("_sign <> 0").select(*(F.col(f"`{c}`") for c in values), "_row_id", "_sign")

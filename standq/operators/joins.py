"""Joins that Spark has no operator for, from its own."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def as_of_join(left: DataFrame, right: DataFrame, column: str, by: list[str], bring: list[str], buckets: str = "month") -> DataFrame:
    """Every left row with ``bring`` of the latest right row of its key that is not later; nulls if there is none.

    One pass over the union, sorted in each key: rows of the right leave their values behind for those after. A hot key
    is cut at calendar ``buckets``; the last right row of each earlier bucket is carried over by a second, small pass.
    Of right rows of one key and time the greatest by the columns ``bring`` counts. A null key or time equals nothing:
    such left rows get nulls, such right rows are met by none.
    """
    value = F.struct(*(F.col(f"`{c}`") for c in bring))
    names = [f"`{c}`" for c in [*by, column]]
    whole = F.lit(True)
    for c in names:
        whole = whole & F.col(c).isNotNull()
    kind = right.select(value.alias("v")).schema["v"].dataType
    a = left.filter(whole).withColumn("_side", F.lit(1)).withColumn("_v", F.lit(None).cast(kind))
    b = right.filter(whole).select(*names, value.alias("_v")).withColumn("_side", F.lit(0))
    both = a.unionByName(b, allowMissingColumns=True).withColumn("_bucket", F.date_trunc(buckets, F.col(f"`{column}`")))
    lasts = both.filter("_side = 0").groupBy(*names[:-1], "_bucket").agg(F.max_by("_v", F.struct(names[-1], "_v")).alias("_last"))
    carried = Window.partitionBy(*names[:-1]).orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    known = both.select(*names[:-1], "_bucket").distinct().join(lasts, [*by, "_bucket"], "left")
    known = known.withColumn("_before", F.last("_last", ignorenulls=True).over(carried)).drop("_last")
    w = Window.partitionBy(*names[:-1], "_bucket").orderBy(names[-1], "_side", "_v").rowsBetween(Window.unboundedPreceding, 0)
    seen = both.withColumn("_seen", F.last(F.when(F.col("_side") == 0, F.col("_v")), ignorenulls=True).over(w)).filter("_side = 1")
    out = seen.join(known, [*by, "_bucket"]).withColumn("_v", F.coalesce("_seen", "_before"))
    out = out.select(*(F.col(f"`{c}`") for c in left.columns), *(F.col("_v")[c].alias(c) for c in bring))
    rest = left.filter(~whole).select("*", *(F.lit(None).cast(right.schema[c].dataType).alias(c) for c in bring))
    return out.unionByName(rest)


def range_join(left: DataFrame, right: DataFrame, at: str, other: str, seconds: int) -> DataFrame:
    """Pairs with other in [at, at + seconds): an equi-join on time cells of that length, each left row in two of them."""
    cell = lambda c: F.floor(F.unix_micros(F.col(c).cast("timestamp")) / (seconds * 1_000_000))
    a = left.withColumn("_cell", F.explode(F.array(cell(at), cell(at) + 1)))
    b = right.withColumn("_cell", cell(other))
    return a.join(b, "_cell").filter((F.col(other) >= F.col(at)) & (F.col(other) < F.col(at) + F.expr(f"interval {seconds} seconds"))).drop("_cell")

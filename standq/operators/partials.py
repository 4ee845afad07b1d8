"""Grouped counts and sums kept from partial sums: a run reads the changed rows and the target's groups, nothing else."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from standq.operators.task import Task
from standq.plans.relation import key_id
from standq.sources.store import Database


@dataclass
class PartialsTask(Task):
    """The target has the keys, ``rows`` (a hidden count, so that an emptied group goes) and one decimal column a sum."""

    keys: list[str] = field(default_factory=list)
    sums: dict[str, str] = field(default_factory=dict)

    def _changes(self, after: int, upto: int) -> DataFrame:
        target = self.db.table(self.target)
        signed = self.source.delta(after, upto)
        moved = signed.groupBy(*self.keys).agg(
            F.sum("_sign").cast("long").alias("rows"), *(F.sum(F.expr(e) * F.col("_sign")).alias(n) for n, e in self.sums.items())
        )
        held = target.snapshot(upto, with_id=True)
        on = F.lit(True)
        for k in self.keys:
            on = on & F.col(f"d.`{k}`").eqNullSafe(F.col(f"t.`{k}`"))
        both = moved.alias("d").join(held.alias("t"), on, "left")
        had = F.col("t._row_id").isNotNull()
        value = lambda n: F.coalesce(F.col(f"t.`{n}`"), F.lit(0)) + F.coalesce(F.col(f"d.`{n}`"), F.lit(0))
        left = value("rows")
        action = F.when(had & (left == 0), "DELETE").when(had, "UPDATE").when(left != 0, "INSERT")
        before = F.when(had, F.struct(*(F.col(f"t.`{c}`").alias(c) for c in target.columns)))
        new = {n: value(n) for n in ("rows", *self.sums)}
        made = both.select(
            *((F.col(f"d.`{f.name}`") if f.name in self.keys else new[f.name]).cast(f.dataType).alias(f.name) for f in target.schema.fields),
            action.alias("_action"), before.alias("_before"),
        )
        return made.withColumn("_row_id", key_id(self.keys)).filter("_action is not null")


def maintain(db: Database, name: str, source, target: str, keys: list[str], sums: dict[str, str], **options) -> PartialsTask:
    """Create the target and the task that keeps it."""
    kinds = dict(source.to_df(0).dtypes)
    columns = [f"{k} {kinds[k]}" for k in keys] + ["rows bigint", *(f"{n} decimal(38,4)" for n in sums)]
    db.create_table(target, ", ".join(columns))
    return PartialsTask(db, name, "apply", source, target, keys=keys, sums=sums, **options)

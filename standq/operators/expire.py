"""Expiration: rows are not expired, expired, or purged. Expiry is not a delete and never shows as a change."""

from __future__ import annotations

import re
import uuid
from datetime import datetime
from typing import Any

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from standq.errors import ExpiredData, StandingQueryError
from standq.plans.prover import require_monotone
from standq.sources.store import Table, log_schema

CLOCK = re.compile(r"\b(?:now\(\)|current_timestamp(?:\(\))?)", re.I)

STRING = re.compile(r"'[^'\\]*'")
RANGE = re.compile(
    r"\s*(?P<column>`[^`]+`|[a-z_]\w*)\s*(?P<op><=|>=|<|>|=)\s*"
    r"(?P<literal>(?P<number>-?\d+(?:\.\d+)?)|(?P<time>(?:date|timestamp_ntz|timestamp)\s*'[^'\\]*')|(?P<string>'[^'\\]*'))\s*", re.I,
)
NUMBERS = {"byte", "short", "integer", "long", "float", "double", "decimal"}


def at_time(predicate: str, now: datetime) -> Column:
    """The policy with the clock at ``now``; unknown is not expired."""
    return F.coalesce(F.expr(CLOCK.sub(f"timestamp_ntz'{now.isoformat(sep=' ')}'", predicate)), F.lit(False))


def set_policy(table: Table, predicate: str | None, mode: str = "add") -> None:
    """``add`` where there is none, ``modify`` the one there is, or ``drop`` it. One at a time."""
    has = table.meta.expire is not None
    if mode == "add" and has:
        raise StandingQueryError(f"{table.name} has an expiration policy")
    if mode != "add" and not has:
        raise StandingQueryError(f"{table.name} has no expiration policy")
    if mode == "drop":
        predicate = None
    else:
        require_monotone(predicate)
    table.meta.expire = predicate
    table.db.save()


def live(table: Table, now: datetime | None = None, on_expired: str = "ignore", where: str = "true") -> DataFrame:
    """Rows of a query over the table. ``ignore`` leaves expired rows out; ``error`` raises if the query touches one, or
    could have touched a purged one."""
    rows = table.snapshot().filter(F.expr(where))
    if table.meta.expire is None:
        return rows
    gone = at_time(table.meta.expire, now or table.db.clock.now())
    if on_expired == "error":
        if not rows.filter(gone).limit(1).isEmpty():
            raise ExpiredData(f"{table.name}: rows expired under: {table.meta.expire}")
        if overlaps(table, where):
            raise ExpiredData(f"{table.name}: rows purged under: {table.meta.expire}")
        return rows
    return rows.filter(~gone)


def final_live(table: Table, where: str = "true", now: datetime | None = None) -> DataFrame:
    """FINAL opts in to the exception: a result is final only if no row of it may have vanished."""
    return live(table, now, "error", where)


def bounds(table: Table, where: str) -> list[tuple[str, str, str]]:
    """(column, comparison, literal) of every plain range that ``where`` demands; what else it demands is left out."""
    bare = STRING.sub(lambda m: "'" + "x" * (len(m[0]) - 2) + "'", where)
    if re.search(r"[()\\\"]|--|/\*|\|\||\b(?:or|not|case|between)\b", bare, re.I):
        return []
    cuts = [0, *(x for m in re.finditer(r"\band\b", bare, re.I) for x in m.span()), len(where)]
    kinds = {f.name.lower(): (f.name, f.dataType.typeName().split("(")[0]) for f in table.schema.fields}
    out = []
    for x, y in zip(cuts[::2], cuts[1::2], strict=True):
        m = RANGE.fullmatch(where[x:y])
        name, kind = kinds.get(m["column"].strip("`").lower(), ("", "")) if m else ("", "")
        fits = {"string": "string", "date": "time string", "timestamp": "time string", "timestamp_ntz": "time string"}.get(kind, "number" if kind in NUMBERS else "")
        if m and any(m[k] for k in fits.split()):  # other pairs of types do not compare in the column's own order
            out.append((name, m["op"], m["literal"]))
    return out


def overlaps(table: Table, where: str) -> bool:
    """Whether a purged row may hold ``where``: the ledger keeps the least and greatest value of each column of what was
    purged. Ruled out only if a plain range that the condition demands of one column misses the box; all else counts as
    an overlap."""
    asked = bounds(table, where)
    for entry in table.meta.purged:
        tests = []
        for c, op, literal in asked:
            if c not in entry["box"]:
                continue
            lo, hi = (F.lit(v).cast(table.schema[c].dataType) for v in entry["box"][c])
            v = F.expr(literal)
            tests.append({"<": lo < v, "<=": lo <= v, ">": hi > v, ">=": hi >= v, "=": (lo <= v) & (hi >= v)}[op])
        if not tests:
            return True
        met = table.db.spark.range(1).select(*(F.coalesce(x, F.lit(False)).alias(f"t{i}") for i, x in enumerate(tests))).first()  # no range holds a null
        if all(met):
            return True
    return False


def row_state(table: Table, now: datetime) -> DataFrame:
    """Rows of each region: not expired, expired, purged."""
    gone = at_time(table.meta.expire, now) if table.meta.expire else F.lit(False)
    stored = table.snapshot().groupBy(F.when(gone, "expired").otherwise("not expired").alias("state")).agg(F.count("*").alias("n"))
    purged = sum(e["rows"] for e in table.meta.purged)
    if purged:
        stored = stored.unionByName(table.db.spark.createDataFrame([("purged", purged)], "state string, n long"))
    return stored


def purge(table: Table, now: datetime, before: str | None = None, archive: str | None = None) -> dict[str, int]:
    """Remove expired rows of an insert-only history from its files, in the background: a file of expired rows alone is
    dropped, a mixed one is written anew without them, others are not touched. The ledger keeps count and value ranges.
    With ``archive`` the rows are moved there first."""
    if table.meta.expire is None:
        raise StandingQueryError(f"{table.name} has no expiration policy")
    gone = at_time(table.meta.expire, now)
    if before is not None:
        gone = gone & F.expr(before)
    plain = [f.name for f in table.schema.fields if f.dataType.typeName() not in ("array", "map", "struct", "binary")]
    spark, done = table.db.spark, {"dropped": 0, "rewritten": 0, "rows": 0}
    fate: dict[str, str | None] = {}  # files that several commits share are looked at once
    for manifest in table.db.manifests:
        entry = manifest["tables"].get(table.name)
        for i, path in enumerate(entry["files"] if entry else []):
            if path in fate:
                entry["files"][i] = fate[path]
                continue
            fate[path] = path
            rows = spark.read.schema(log_schema(table.schema)).parquet(path)
            seen = rows.agg(
                F.count("*").alias("n"), F.sum(gone.cast("long")).alias("g"),
                *(f(F.when(gone, F.col(f"`{c}`"))).cast("string").alias(f"{k}_{c}") for c in plain for k, f in (("lo", F.min), ("hi", F.max))),
            ).first()
            if not seen.g:
                continue
            if archive:
                rows.filter(gone).write.mode("append").parquet(archive)
            new = f"{table.db.root}/data/{table.name}/purged-{uuid.uuid4().hex}"
            if seen.g == seen.n:
                entry["files"][i] = fate[path] = None
                done["dropped"] += 1
            else:
                rows.filter(~gone).write.parquet(new)
                entry["files"][i] = fate[path] = new
                done["rewritten"] += 1
            done["rows"] += seen.g
            table.meta.purged.append({"rows": seen.g, "box": {c: [seen[f"lo_{c}"], seen[f"hi_{c}"]] for c in plain}})
        if entry and None in entry["files"]:
            entry["files"] = [f for f in entry["files"] if f]
        if entry:
            table.db.log.replace(f"_manifest/{manifest['commit']:020d}.json", manifest)
    table.db.gather_manifests()
    table.db.save()
    return done


def compare_policies(table: Table, old: str, new: str, now: datetime) -> dict[str, Any]:
    """How a new policy differs on the rows there are: widens, narrows, same or incomparable. Purged rows do not return."""
    a, b = at_time(old, now), at_time(new, now)
    r = table.snapshot().agg(F.sum((a & ~b).cast("long")).alias("only_old"), F.sum((b & ~a).cast("long")).alias("only_new")).first()
    only_old, only_new = r.only_old or 0, r.only_new or 0
    kind = "incomparable" if only_old and only_new else "narrows" if only_old else "widens" if only_new else "same"
    return {"only_old": only_old, "only_new": only_new, "kind": kind, "warn_purged": bool(only_old and table.meta.purged)}

"""Readers and writers around versioned tables."""

from __future__ import annotations

from collections.abc import Iterator
from typing import Any

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T
from pyspark.sql.datasource import DataSource, SimpleDataSourceStreamReader

from standq.sources.store import Database, Table


def ingest(db: Database, name: str, rows: DataFrame, key: list[str] | None = None, insert_only: bool = True) -> Table:
    """A new table with one commit of these rows."""
    table = db.create_table(name, rows.schema, key, insert_only)
    with db.transaction() as tx:
        tx.insert(name, rows)
    return table


def ingest_files(db: Database, name: str, form: str, path: str, schema: T.StructType | str | None = None, key: list[str] | None = None, **options: Any) -> Table:
    """parquet, csv, json, orc or text files as a table. Give a schema for csv and json: without one the files are read twice."""
    reader = db.spark.read.format(form).options(**options)
    return ingest(db, name, (reader.schema(schema) if schema else reader).load(path), key)


def ingest_jdbc(db: Database, name: str, url: str, table: str, key: list[str], **options: Any) -> int:
    """Rows of an outside database: the first time as they are, later as the difference to what is held."""
    rows = db.spark.read.format("jdbc").options(url=url, dbtable=table, **options).load()
    return follow_snapshot(db, name, rows, key)


def follow_snapshot(db: Database, name: str, rows: DataFrame, key: list[str]) -> int:
    """Bring a keyed table up to a full extract of its source, in one commit of inserts, updates and deletes."""
    from pyspark.sql import functions as F

    from standq.sources.store import Transaction, row_ids

    if name not in db.metas:
        ingest(db, name, rows, key, insert_only=False)
        return db.version
    table, tx = db.table(name), Transaction(db)
    names = table.columns
    new = rows.select(*(F.col(f"`{c}`").alias(f"n_{c}") for c in names))
    old = table.snapshot(with_id=True).select(*(F.col(f"`{c}`").alias(f"o_{c}") for c in names), "_row_id")
    on = F.lit(True)
    for k in key:
        on = on & (F.col(f"n_{k}") == F.col(f"o_{k}"))
    is_new, was = F.col(f"n_{key[0]}").isNotNull(), F.col("_row_id").isNotNull()
    same = F.lit(True)
    for c in names:
        same = same & F.col(f"n_{c}").eqNullSafe(F.col(f"o_{c}"))
    action = F.when(~was, "INSERT").when(~is_new, "DELETE").when(~same, "UPDATE")
    made = new.join(old, on, "full_outer").select(
        *(F.when(is_new, F.col(f"n_{c}")).otherwise(F.col(f"o_{c}")).alias(c) for c in names), action.alias("_action"),
        "_row_id", F.when(was, F.struct(*(F.col(f"o_{c}").alias(c) for c in names))).alias("_before"),
    ).filter("_action is not null")
    made = made.withColumn("_row_id", F.coalesce("_row_id", row_ids(F.lit(tx.number), F.lit(1))))
    tx.apply(name, made)
    tx.commit()
    return db.version


def export(rows: DataFrame, form: str, path: str, partition_by: list[str] | None = None) -> None:
    writer = rows.write.format(form).mode("overwrite")
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


class _Commits(SimpleDataSourceStreamReader):
    def __init__(self, folder: str):
        self.folder = folder

    def initialOffset(self) -> dict[str, int]:
        return {"commit": 0}

    def _numbers(self) -> list[int]:
        from pyarrow import fs

        source, place = fs.FileSystem.from_uri(self.folder)
        found = source.get_file_info(fs.FileSelector(place, allow_not_found=True))
        return sorted(int(f.base_name.split(".")[0]) for f in found if f.base_name[:1].isdigit())

    def read(self, start: dict[str, int]) -> tuple[Iterator[tuple], dict[str, int]]:
        numbers = [n for n in self._numbers() if n > start["commit"]]
        return iter([(n,) for n in numbers]), {"commit": numbers[-1] if numbers else start["commit"]}

    def readBetweenOffsets(self, start: dict[str, int], end: dict[str, int]) -> Iterator[tuple]:
        return iter([(n,) for n in range(start["commit"] + 1, end["commit"] + 1)])


class CommitTicker(DataSource):
    """A stream of commit numbers, for queries that wake at a commit. Rows themselves do not go through it."""

    @classmethod
    def name(cls) -> str:
        return "standq_commits"

    def schema(self) -> str:
        return "commit_no bigint"

    def simpleStreamReader(self, schema: T.StructType) -> _Commits:
        return _Commits(self.options["path"].rstrip("/") + "/_manifest")


def commit_stream(spark: SparkSession, root: str) -> DataFrame:
    spark.dataSource.register(CommitTicker)
    return spark.readStream.format("standq_commits").option("path", root).load()

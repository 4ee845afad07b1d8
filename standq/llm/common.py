"""Shared plumbing: code shipping, staged tables, and an Arrow row-annotator."""

from __future__ import annotations

import tempfile
import zipfile
from collections.abc import Callable, Iterator
from pathlib import Path

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from standq.scratch import scratch

#: Rows of one Arrow batch given to Python. Texts are long, so batches are kept small to bound a worker's memory.
BATCH_ROWS = 1000

_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Make this package importable on every executor, once per application, and bound Arrow batches."""
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) > BATCH_ROWS:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    root = Path(__file__).resolve().parents[1]
    out = Path(tempfile.mkdtemp(prefix="standq-code-")) / "standq_code.zip"
    with zipfile.ZipFile(out, "w") as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, str(Path(root.name) / p.relative_to(root)))
    spark.sparkContext.addPyFile(str(out))
    _shipped.add(app)


def staged(df: DataFrame, name: str) -> DataFrame:
    """Cut the lineage: write ``df`` to the shared folder and read it again."""
    spark = df.sparkSession
    path = f"{scratch(spark)}/{name}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop_staged(df: DataFrame) -> None:
    """Delete the files behind a staged table that nothing needs any longer."""
    spark = df.sparkSession
    for f in {p.rsplit("/", 1)[0] for p in df.inputFiles()}:
        if "/standq-" in f:
            path = spark._jvm.org.apache.hadoop.fs.Path(f)
            path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


#: Rows of one key beyond which a join deals them to several tasks.
HOT = 200_000


def join_hot(left: DataFrame, right: DataFrame, key: str, n: str, hot: int | None = None) -> DataFrame:
    """Inner join on ``key``, which is unique on the right, where ``n`` tells how many rows of the left have it. Rows of a
    key with more than ``hot`` are dealt to as many tasks as that takes; its right row goes to each of them."""
    hot = hot or HOT
    many = F.ceil(F.col(n) / hot).cast("int")
    keys = staged(right.filter(F.col(n) > hot).select(key, many.alias("_deal")), "hot")
    if keys.isEmpty():
        return left.join(right, key)
    few = F.broadcast(keys) if keys.count() <= 100_000 else keys  # at most one for every ``hot`` rows of the left
    dealt = left.join(few, key, "left").withColumn("_part", F.coalesce(F.pmod(F.monotonically_increasing_id(), F.col("_deal")), F.lit(0)).cast("int"))
    spread = right.withColumn("_part", F.explode(F.sequence(F.lit(0), F.greatest(many, F.lit(1)) - 1)))
    return dealt.drop("_deal").join(spread, [key, "_part"]).drop("_part")


def annotate(
    df: DataFrame,
    fn: Callable[[], Callable[[pa.RecordBatch], dict[str, list]]],
    fields: list[T.StructField],
    needs: list[str],
    keep: list[str] | None = None,
) -> DataFrame:
    """Add columns to every row with a Python function over Arrow batches.

    ``fn()`` is called once a task and returns the batch function, so costly set-up is per task. ``needs`` are the
    columns read; ``keep`` are the input columns kept as they are (all, if None). An input column named as a new one
    gives way.
    """
    ship(df.sparkSession)
    names = [f.name for f in fields]
    new = {n.lower() for n in names}
    kept = [c for c in (df.columns if keep is None else keep) if c.lower() not in new]
    source = df.select(*(F.col(f"`{c}`") for c in dict.fromkeys([*kept, *needs])))
    by_name = {f.name: f for f in source.schema.fields}
    schema = T.StructType([*(by_name[c] for c in kept), *fields])
    arrow = to_arrow_schema(schema)
    asked = source.columns
    positions = [asked.index(c) for c in kept]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work = None
        for batch in batches:
            if not batch.num_rows:
                continue
            work = work or fn()
            batch = pa.RecordBatch.from_arrays(batch.columns, names=asked)
            made = work(batch)
            columns = [batch.column(i) for i in positions]
            columns += [pa.array(made[n], type=arrow.field(n).type) for n in names]
            fixed = pa.schema([*(batch.schema.field(i) for i in positions), *(arrow.field(n) for n in names)])
            yield pa.RecordBatch.from_arrays(columns, schema=fixed)

    return source.toDF(*(f"c{i}" for i in range(len(asked)))).mapInArrow(run, schema)  # names may hold dots


def free(df: DataFrame, name: str) -> str:
    """The name, with underscores before it until no column has it (in any case of letters)."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = "_" + name
    return name


def texts(batch: pa.RecordBatch, column: str) -> list[str]:
    """The text column as strings; null counts as empty."""
    return [t or "" for t in batch.column(batch.schema.get_field_index(column)).to_pylist()]

"""Embedding near-duplicates: exact cosine links by PCA-ordered tiled comparison.

Equal vectors are one class first. Unit vectors are turned into principal axes, so the leading dimensions hold most of
a product. Tiles of classes, dealt by the first axis, are compared pair by pair: the leading dimensions are multiplied
first, what is left is at most the product of the suffix norms, and only pairs whose sum can still reach the threshold
go on to the next dimensions. What reaches the threshold is decided in double precision.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import join_hot, ship, staged
from .components import components, unite
from .simhash import typed

#: Rows of a tile: a sixth of all, so that there is work for some twenty tasks and a row moves some six times, between
#: the least that is worth a task and what takes so many bytes in double precision.
LEAST_TILE, TILE_BYTES = 1024, 32 << 20
LEADING = 16
#: Room for rounding: bounds in single precision, and products that are decided again on the vectors as given.
SLACK, CLOSE = 1e-4, 1e-9


def matrix(column) -> np.ndarray:
    """A list column of equal lengths as a matrix in double precision."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    if not len(column):
        return np.zeros((0, 0))
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(column), -1)


def unit(x: np.ndarray) -> np.ndarray:
    """Rows of length one. Scaled by the largest component first, so that no square over- or underflows."""
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def principal_axes(classes: DataFrame, dim: int) -> np.ndarray:
    """Orthonormal axes by falling second moment of all unit vectors (columns)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((dim, dim))
        for batch in batches:
            x = unit(matrix(batch.column(0)))
            total += x.T @ x
        yield pa.RecordBatch.from_pydict({"i": list(range(dim)), "v": total.tolist()})

    made = classes.select("vec").mapInArrow(typed(run, "i int, v array<double>"), "i int, v array<double>")
    cells = made.select("i", F.posexplode("v").alias("j", "v")).groupBy("i", "j").agg(F.sum("v").alias("v"))
    moment = np.zeros((dim, dim))
    for r in cells.collect():  # dim x dim numbers
        moment[r.i, r.j] = r.v
    _, axes = np.linalg.eigh((moment + moment.T) / 2)
    return axes[:, ::-1].copy()


def compare(a: np.ndarray, b: np.ndarray, raw_a: np.ndarray, raw_b: np.ndarray, threshold: float, same: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs with cosine >= threshold; ``a``, ``b`` are unit rows in principal axes. Within a tile i < j."""
    dim = a.shape[1]
    lead = min(LEADING, dim)
    steps = [*range(lead, dim, LEADING), dim]
    tail = lambda x, k: np.sqrt(np.maximum(0.0, 1.0 - np.square(x[:, :k]).sum(axis=1)))
    tails = {k: (tail(a, k), tail(b, k)) for k in steps}
    head = lambda x, t: np.concatenate([x[:, :lead], t[:, None]], axis=1).astype(np.float32)
    ha, hb = head(a, tails[lead][0]), head(b, tails[lead][1]).T
    rows = max(1, (1 << 22) // max(len(b), 1))
    for at in range(0, len(a), rows):
        bound = ha[at : at + rows] @ hb
        i, j = np.nonzero(bound >= threshold - SLACK)
        if same:
            up = i + at < j
            i, j = i[up], j[up]
        for c in range(0, len(i), 100_000):
            p, q = i[c : c + 100_000] + at, j[c : c + 100_000]
            value, done = np.zeros(len(p)), 0
            for k in steps:
                value = value + np.einsum("ij,ij->i", a[p, done:k], b[q, done:k])
                can = value + tails[k][0][p] * tails[k][1][q] >= threshold - CLOSE if k < dim else value >= threshold - CLOSE
                p, q, value, done = p[can], q[can], value[can], k
            near = np.flatnonzero(np.abs(value - threshold) < CLOSE)
            sure = value >= threshold
            for n in near.tolist():
                x, y = raw_a[p[n]], raw_b[q[n]]
                sure[n] = math.fsum(x * y) / math.sqrt(math.fsum(x * x) * math.fsum(y * y)) >= threshold
            if sure.any():
                yield p[sure], q[sure]


def tile_links(tiles: DataFrame, pairs: DataFrame, axes: np.ndarray, threshold: float) -> DataFrame:
    """(cid, links, root): for every class of a pair of tiles with a link, the vectors it links with, and the least
    class of the set that these links connect."""
    spark = tiles.sparkSession
    turn = spark.sparkContext.broadcast(axes)  # dim x dim numbers

    def run(table: pa.Table) -> pa.Table:
        side = table.column("tile").to_numpy()
        cid, n, raw = table.column("cid").to_numpy(), table.column("n").to_numpy(), matrix(table.column("vec"))
        x = unit(raw) @ turn.value
        names = np.unique(side)
        where = [np.flatnonzero(side == t) for t in names]
        left, right = where[0], where[-1]
        total, labels = np.zeros(len(cid), np.int64), np.arange(len(cid))
        order = np.argsort(cid, kind="stable")
        rank = np.empty(len(cid), np.int64)
        rank[order] = np.arange(len(cid))
        for p, q in compare(x[left], x[right], raw[left], raw[right], threshold, len(names) == 1):
            i, j = left[p], right[q]
            np.add.at(total, i, n[j])
            np.add.at(total, j, n[i])
            unite(labels, rank[i], rank[j])
        own = np.flatnonzero(total)
        return pa.table({"cid": cid[own], "links": total[own], "root": cid[order[labels[rank[own]]]]})

    asked = pairs.select("pair", F.explode(F.array_distinct(F.array("ta", "tb"))).alias("tile"))
    dealt = asked.join(tiles, "tile")
    return dealt.select("pair", "tile", "cid", "n", "vec").groupBy("pair").applyInArrow(run, "cid long, links long, root long")


def tiled(classes: DataFrame, axes: np.ndarray, count: int, reach: float, tile: int) -> tuple[DataFrame, DataFrame]:
    """Classes with a tile of at most about ``tile`` rows, by the first axis; and the pairs of tiles within reach."""
    axis = axes[:, 0]

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = unit(matrix(batch.column(2))) @ axis
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(x)], names=["cid", "n", "vec", "x"])

    kind = classes.schema["vec"].dataType.simpleString()
    placed = staged(classes.select("cid", "n", "vec").mapInArrow(first, f"cid long, n long, vec {kind}, x double"), "placed")
    parts = -(-count // tile)
    cuts = placed.approxQuantile("x", [k / parts for k in range(1, parts)], min(0.01, 0.1 / parts)) if parts > 1 else []
    strip = F.lit(0)
    if cuts:
        bounds = F.array(*map(F.lit, sorted(set(cuts)))) if len(cuts) <= 1000 else None
        strip = F.size(F.filter(bounds, lambda c: c <= F.col("x"))) if bounds is not None else F.floor((F.col("x") + 1) * parts).cast("int")
    placed = placed.withColumn("strip", strip)
    sizes = placed.groupBy("strip").agg(F.count("*").alias("rows"))
    split = F.pmod(F.xxhash64("cid"), F.greatest(F.lit(1), F.ceil(F.col("rows") / tile)))
    sizes = staged(sizes, "strips")  # a row a strip, and there are about as many strips as tiles
    tiles = placed.join(F.broadcast(sizes) if parts <= 1_000_000 else sizes, "strip").withColumn("tile", F.col("strip").cast("long") * 1_000_000 + split)
    tiles = staged(tiles.select("tile", "cid", "n", "vec", "x"), "tiles")
    boxes = staged(tiles.groupBy("tile").agg(F.min("x").alias("lo"), F.max("x").alias("hi")), "boxes")
    cell = lambda c: F.floor(c / reach)
    a = boxes.select(F.col("tile").alias("ta"), F.col("hi").alias("ahi"), F.col("lo").alias("alo"), F.explode(F.sequence(cell(F.col("lo")) - 1, cell(F.col("hi")) + 1)).alias("cell"))
    b = boxes.select(F.col("tile").alias("tb"), F.col("lo").alias("blo"), F.col("hi").alias("bhi"), F.explode(F.sequence(cell(F.col("lo")), cell(F.col("hi")))).alias("cell"))
    pairs = a.join(b, "cell").filter((F.col("ta") <= F.col("tb")) & (F.col("blo") - F.col("ahi") <= reach) & (F.col("alo") - F.col("bhi") <= reach))
    pairs = pairs.select("ta", "tb").distinct().withColumn("pair", F.struct("ta", "tb"))
    return tiles, pairs


def near_duplicates(vectors: DataFrame, threshold: float = 0.9, id_col: str = "vec_id", vec_col: str = "embedding", tile: int | None = None) -> DataFrame:
    """One row a vector: ``id_col``, n_links (other vectors with cosine >= threshold), component_id (least identifier
    reachable, itself included), kept (is its own component's least).

    Null, empty and zero vectors, and vectors with null or non-finite components, link with nothing; vectors of
    different lengths don't link with one another. Repeated rows are vectors of their own. Null identifiers are never
    the least. An empty table gives an empty one; other columns are not read. ``threshold`` must be above 0.
    """
    spark = vectors.sparkSession
    ship(spark)
    vec = F.col("vec")
    finite = F.forall(vec, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < F.lit(float("inf"))))
    good = F.coalesce(vec.isNotNull() & finite & F.exists(vec, lambda v: v != 0), F.lit(False))
    rows = vectors.select(F.col(f"`{id_col}`").alias("id"), F.col(f"`{vec_col}`").alias("vec")).withColumn("good", good)
    own = rows.filter("good")
    made = own.groupBy("vec").agg(F.min("id").alias("least"), F.count("*").alias("n"))
    classes = staged(made.withColumn("cid", F.monotonically_increasing_id()), "classes")
    found, reach = None, math.sqrt(max(0.0, 2 - 2 * threshold)) + 1e-6
    for r in classes.groupBy(F.size("vec").alias("dim")).agg(F.count("*").alias("n")).collect():  # one row a vector length
        part = classes.filter(F.size("vec") == r.dim)
        axes = principal_axes(part, r.dim)
        size = tile or min(max(LEAST_TILE, TILE_BYTES // (8 * r.dim)), max(LEAST_TILE, -(-r.n // 6)))
        links = tile_links(*tiled(part, axes, r.n, reach, size), axes, threshold)
        found = links if found is None else found.unionByName(links)
    if found is None:
        found = spark.createDataFrame([], "cid long, links long, root long")
    found = staged(found, "links")
    counts = found.groupBy("cid").agg(F.sum("links").alias("links"))
    joined = components(found.select(F.col("cid").alias("a"), F.col("root").alias("b"))).select(F.col("node").alias("cid"), "root")
    whole = classes.join(counts, "cid", "left").join(joined, "cid", "left").withColumn("root", F.coalesce("root", "cid"))
    whole = staged(whole.select("vec", "n", "least", "root", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links")), "whole")
    least = whole.groupBy("root").agg(F.min("least").alias("component_id"))
    named = staged(whole.join(least, "root").select("vec", "n", "n_links", "component_id"), "named")
    linked = join_hot(own, named, "vec", "n").select("id", "n_links", "component_id")
    alone = rows.filter(~F.col("good")).select("id", F.lit(0).cast("long").alias("n_links"), F.col("id").alias("component_id"))
    out = linked.unionByName(alone).withColumn("kept", F.coalesce(F.col("id") == F.col("component_id"), F.lit(False)))
    return out.withColumnRenamed("id", id_col)


def op2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))

"""Connected components of an edge table by repeated contraction, and a small in-task union for tiles."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop_staged, staged


def components(edges: DataFrame, a: str = "a", b: str = "b", most_rounds: int = 60) -> DataFrame:
    """(node, root) for every node that has an edge; nodes share a root exactly if edges connect them.

    Each round every node points to the neighbour (or itself) of least random rank, and edges are redrawn between the
    nodes pointed to. Random ranks make the graph shrink by a factor each round whatever its shape, chains too. A node's
    neighbours meet only in a minimum that is pre-aggregated before the shuffle. Every round is cut by a staged table.
    Null ends and self-links are ignored; repeated links do no harm; an empty table gives an empty one.
    """
    link = edges.select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b")).filter("a <> b")
    link = staged(link, "links")
    labels = None
    for turn in range(most_rounds):
        if link.isEmpty():
            break
        rank = lambda c, turn=turn: F.struct(F.xxhash64(F.col(c), F.lit(turn)).alias("r"), F.col(c).alias("n"))
        both = link.select("a", rank("b").alias("p")).union(link.select(F.col("b").alias("a"), rank("a").alias("p")))
        best = both.groupBy("a").agg(F.min("p").alias("p"))
        points = staged(best.select("a", F.least(F.col("p"), rank("a")).getField("n").alias("to")), "points")
        labels = points.select(F.col("a").alias("node"), F.col("to").alias("root")) if labels is None else (
            labels.join(points.select(F.col("a").alias("root"), "to"), "root", "left").select("node", F.coalesce("to", "root").alias("root"))
        )
        moved = link.join(points.withColumnRenamed("to", "ra"), "a").join(points.select(F.col("a").alias("b"), F.col("to").alias("rb")), "b")
        moved = moved.filter("ra <> rb").select(F.least("ra", "rb").alias("a"), F.greatest("ra", "rb").alias("b")).distinct()
        before, link = link, staged(moved, "links")
        drop_staged(before)
    else:
        raise RuntimeError("components did not settle")
    if labels is None:
        return link.select(F.col("a").alias("node"), F.col("b").alias("root"))
    return staged(labels, "labels")


def unite(labels: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Join the sets of a[i] and b[i]; ``labels`` holds each element's root, the least index of its set."""
    while True:
        ra, rb = labels[a], labels[b]
        differ = ra != rb
        if not differ.any():
            return
        a, b, ra, rb = a[differ], b[differ], ra[differ], rb[differ]
        np.minimum.at(labels, np.maximum(ra, rb), np.minimum(ra, rb))
        while True:
            up = labels[labels]
            if np.array_equal(up, labels):
                break
            labels[:] = up

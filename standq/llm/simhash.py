"""SimHash near-duplicates by generalised pigeonhole.

Exact copies meet in their fingerprint first. Distinct fingerprints within ``tau`` bits are then found so: bits are
dealt into groups, correlated ones together; every group gets a threshold of its own, -1 (not used) or more, such that
the thresholds plus one add up to tau + 1; so any linked pair is within the threshold in some group. Groups and
thresholds are chosen by dynamic programming on candidate counts estimated from all fingerprints. A fingerprint is
filed under its value in each group and probes the values within the threshold; what meets is verified on all 64 bits.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import annotate, free, join_hot, ship, staged, texts
from .components import components, unite

BITS = 64
#: A bucket of more rows is cut into tiles, and each pair of tiles is a task's work of its own.
TILE = 16_384
#: A probe row (written, moved, sorted) costs as much as so many comparisons of two fingerprints.
PROBE_COST = 60.0


def fingerprint(text: str, words: int = 4, seed: int = 42) -> int:
    """Majority bits of the hashes of all word shingles; no words give zero."""
    parts = text.encode("utf-8", "surrogatepass").lower().split()  # bytes: A-Z and ASCII blanks alone
    if not parts:
        return 0
    joined = b" ".join(parts)
    if len(parts) <= words:
        return xxhash.xxh64_intdigest(joined, seed)
    ends = np.cumsum(np.fromiter(map(len, parts), np.int64, len(parts)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    hashed = xxhash.xxh64_digest
    first, last = starts[: len(parts) - words + 1].tolist(), ends[words - 1 :].tolist()
    total = np.zeros(BITS, np.int64)
    for at in range(0, len(first), 1 << 16):
        raw = b"".join([hashed(joined[x:y], seed) for x, y in zip(first[at : at + (1 << 16)], last[at : at + (1 << 16)], strict=True)])
        total += np.unpackbits(np.frombuffer(raw, np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * total > len(first)).tobytes(), "big")


def signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


def with_fingerprints(docs: DataFrame, text_col: str = "text", out: str = "fp", keep: list[str] | None = None) -> DataFrame:
    """``docs`` (or its columns ``keep``) with the fingerprint as a signed long. Null text counts as empty."""

    def start():
        return lambda batch: {out: [signed(fingerprint(t)) for t in texts(batch, text_col)]}

    return annotate(docs, start, [T.StructField(out, T.LongType())], [text_col], keep)


def bit_statistics(prints: DataFrame, words: tuple[str, ...] = ("fp",)) -> tuple[int, np.ndarray]:
    """Number of fingerprints (of 64 bits a column of ``words``), and how often each two bits are both set, over all."""
    bits = BITS * len(words)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        both, n = np.zeros((bits, bits), np.int64), 0
        for batch in batches:
            x = np.concatenate([spread(c.to_numpy().view(np.uint64)) for c in batch.columns], axis=1).astype(np.float32)
            both += np.rint(x.T @ x).astype(np.int64)
            n += len(x)
        if n:
            yield pa.RecordBatch.from_pydict({"i": list(range(bits)), "n": [n] * bits, "c": both.tolist()})

    made = prints.select(*words).mapInArrow(typed(run, "i int, n long, c array<long>"), "i int, n long, c array<long>")
    rows = made.groupBy("i").agg(F.sum("n").alias("n"), F.array(*(F.sum(F.col("c")[j]) for j in range(bits))).alias("c")).collect()  # one row a bit
    both = np.zeros((bits, bits))
    for r in rows:
        both[r.i] = r.c
    return (rows[0].n if rows else 0), both


def typed(run, kinds: str):
    """Give the batches of ``run`` the types of a schema string."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    schema = to_arrow_schema(_parse_datatype_string(kinds))

    def cast(batches):
        for b in run(batches):
            yield pa.RecordBatch.from_arrays([b.column(f.name).cast(f.type) for f in schema], schema=schema)

    return cast


def spread(x: np.ndarray) -> np.ndarray:
    """Bits of unsigned 64-bit numbers, one column a bit, bit 0 the least."""
    return ((x[:, None] >> np.arange(BITS, dtype=np.uint64)) & np.uint64(1)).astype(np.uint8)


@dataclass(frozen=True)
class Plan:
    groups: tuple[tuple[int, ...], ...]
    limits: tuple[int, ...]
    cost: float


def grouped(correlation: np.ndarray, m: int) -> list[list[int]]:
    """m groups of about equal size; a group takes the bit that correlates most with those it has."""
    bits = len(correlation)
    free, out = np.ones(bits, bool), []
    rest = correlation.sum(axis=1) - np.diag(correlation)  # with the bits that are free
    for g in range(m):
        own, near = [], np.zeros(bits)
        for k in range(bits // m + (g < bits % m)):
            pick = int(np.argmax(np.where(free, near if k else rest, -np.inf)))
            own.append(pick)
            free[pick] = False
            near = near + correlation[:, pick]
            rest = rest - correlation[:, pick]
        out.append(own)
    return out


def apart(agree: np.ndarray, joint: np.ndarray | None, bits: list[int]) -> np.ndarray:
    """Chances that two fingerprints differ in 0, 1, .. of these bits.

    Of independent bits it is their convolution. Where bits agree together more often than by chance (``joint``: the
    chance that both of two bits agree), a beta-binomial of the same mean and variance.
    """
    mean = float((1 - agree[bits]).sum())
    if joint is not None:
        own = joint[np.ix_(bits, bits)] - np.outer(agree[bits], agree[bits])
        np.fill_diagonal(own, agree[bits] * (1 - agree[bits]))
        w, q, var = len(bits), mean / len(bits), float(own.sum())
        rho = (var / max(w * q * (1 - q), 1e-12) - 1) / max(w - 1, 1)
        if 1e-6 < rho < 1 - 1e-6 and 0 < q < 1:
            a, b = q * (1 / rho - 1), (1 - q) * (1 / rho - 1)
            lg = math.lgamma
            row = [math.comb(w, k) * math.exp(lg(k + a) + lg(w - k + b) - lg(w + a + b) - lg(a) - lg(b) + lg(a + b)) for k in range(w + 1)]
            return np.array(row)
    out = np.array([1.0])
    for i in bits:
        out = np.convolve(out, [agree[i], 1 - agree[i]])
    return out


def allocate(n: int, agree: np.ndarray, groups: list[list[int]], tau: int, joint: np.ndarray | None = None, probe: float = PROBE_COST) -> Plan:
    """Thresholds of least estimated cost with sum(t + 1) = tau + 1, by dynamic programming over the groups."""
    costs = []
    for g in groups:
        chance, row = apart(agree, joint, g), [0.0]
        for t in range(tau + 1):
            ball = sum(math.comb(len(g), k) for k in range(t + 1))
            row.append(n * (1 + (ball - 1) / 2) * probe + n * n / 2 * chance[: t + 1].sum())
        costs.append(row)
    best: dict[int, tuple[float, tuple[int, ...]]] = {0: (0.0, ())}
    for row in costs:
        step: dict[int, tuple[float, tuple[int, ...]]] = {}
        for used, (cost, chosen) in best.items():
            for t1 in range(tau + 2 - used):
                to = (cost + row[t1], (*chosen, t1 - 1))
                if used + t1 not in step or to < step[used + t1]:
                    step[used + t1] = to
        best = step
    cost, limits = best[tau + 1]
    return Plan(tuple(tuple(g) for g in groups), limits, cost)


def plan_groups(n: int, both: np.ndarray, tau: int, probe: float = PROBE_COST, numbers: tuple[int, ...] | None = None) -> Plan:
    """Groups (in one of the ``numbers``) and thresholds of least cost, from how often each two bits are set together."""
    two = both / max(n, 1)
    p = np.diag(two)
    deviation = np.sqrt(np.maximum(p * (1 - p), 1e-12))
    correlation = np.abs(two - np.outer(p, p)) / np.outer(deviation, deviation)
    agree = p * p + (1 - p) * (1 - p)
    one = p[:, None] - two  # the first bit set and not the second
    neither = 1 - p[:, None] - p[None, :] + two
    joint = two**2 + one**2 + one.T**2 + neither**2
    return min((allocate(n, agree, grouped(correlation, m), tau, joint, probe) for m in numbers or range(2, tau + 2)), key=lambda x: x.cost)


def probes(prints: DataFrame, plan: Plan) -> DataFrame:
    """(bucket, kind, fp): kind 0 files a fingerprint under its own value, 1 probes a greater value nearby.

    A probe of a smaller value is not needed: that pair meets when the other one probes.
    """
    used = [(i, g, t) for i, (g, t) in enumerate(zip(plan.groups, plan.limits, strict=True)) if t >= 0]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = batch.column(0).to_numpy().view(np.uint64)
            for i, bits, t in used:
                value = np.zeros(len(x), np.uint64)
                for k, b in enumerate(bits):
                    value |= ((x >> np.uint64(b)) & np.uint64(1)) << np.uint64(k)
                for r in range(t + 1):
                    for flips in combinations(range(len(bits)), r):
                        mask = np.uint64(sum(1 << k for k in flips))
                        other = value ^ mask
                        up = other > value if r else np.ones(len(x), bool)
                        if up.any():
                            at = (other[up] * np.uint64(8) + np.uint64(i)).view(np.int64)
                            yield pa.RecordBatch.from_pydict({"bucket": at, "kind": np.full(len(at), min(r, 1), np.int8), "fp": x[up].view(np.int64)})

    kinds = "bucket long, kind tinyint, fp long"
    return prints.select("fp").mapInArrow(typed(run, kinds), kinds)


def bucket_links(fps: np.ndarray, kinds: np.ndarray, tau: int) -> tuple[np.ndarray, np.ndarray]:
    """Links that connect what the pairs of one bucket connect: a star to the least of each connected set."""
    x = fps.view(np.uint64)
    labels = np.arange(len(x))
    filed = np.flatnonzero(kinds == 0)
    step = max(1, (1 << 21) // max(len(x), 1))
    for at in range(0, len(filed), step):
        rows = filed[at : at + step]
        i, j = np.nonzero(np.bitwise_count(x[rows, None] ^ x[None, :]) <= tau)
        unite(labels, rows[i], j)
    own = np.flatnonzero(labels != np.arange(len(x)))
    return fps[own], fps[labels[own]]


def links(rows: DataFrame, tau: int) -> DataFrame:
    """(a, b) links of the buckets; rows of a bucket lie together in a partition, sorted."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        size = 0

        def work(key, kind, fp):
            """Whole buckets. Short ones are compared by shifting the columns against themselves."""
            starts = np.concatenate(([0], np.flatnonzero(key[1:] != key[:-1]) + 1, [len(key)]))
            sizes = np.diff(starts)
            wide = np.repeat(sizes, sizes)
            out_a, out_b = [], []
            small = np.flatnonzero((wide > 1) & (wide <= 8))
            if small.size:
                k, c, x = key[small], kind[small], fp[small]
                for d in range(1, 8):
                    if len(k) <= d:
                        break
                    ok = (k[d:] == k[:-d]) & ((c[d:] == 0) | (c[:-d] == 0)) & (np.bitwise_count((x[d:] ^ x[:-d]).view(np.uint64)) <= tau)
                    out_a.append(x[d:][ok])
                    out_b.append(x[:-d][ok])
            for b in np.flatnonzero(sizes > 8).tolist():
                s, e = starts[b], starts[b + 1]
                a, c = bucket_links(fp[s:e], kind[s:e], tau)
                out_a.append(a)
                out_b.append(c)
            if out_a:
                a, b = np.concatenate(out_a), np.concatenate(out_b)
                if len(a):
                    yield pa.RecordBatch.from_pydict({"a": np.minimum(a, b), "b": np.maximum(a, b)})

        for batch in batches:
            key, kind, fp = (c.to_numpy() for c in batch.columns[:3])
            held.append((key, kind, fp))
            size += len(key)
            if held[0][0][0] == key[-1] or size < 65_536:  # the bucket goes on, or there is little to do yet
                continue
            key, kind, fp = (np.concatenate(c) for c in zip(*held, strict=True))
            cut = int(np.flatnonzero(key != key[-1])[-1]) + 1
            yield from work(key[:cut], kind[:cut], fp[:cut])
            held, size = [(key[cut:], kind[cut:], fp[cut:])], len(key) - cut
        if held:
            yield from work(*(np.concatenate(c) for c in zip(*held, strict=True)))

    return rows.select("bucket", "kind", "fp").mapInArrow(typed(run, "a long, b long"), "a long, b long").distinct()


def cut_hot(rows: DataFrame, tile: int = TILE, by: str = "fp") -> DataFrame:
    """Give every row of a bucket beyond ``tile`` rows one copy for each pair of tiles that its own is in; tiles are
    dealt by hash of ``by``. Of such a bucket in which nothing is filed no row is left, for it has no pair."""
    hot = rows.groupBy("bucket").agg(F.count("*").alias("n"), F.sum((F.col("kind") == 0).cast("long")).alias("filed"))
    tiles = F.when(F.col("filed") > 0, F.ceil(F.col("n") / tile)).otherwise(0).cast("int")
    hot = staged(hot.filter(F.col("n") > tile).select("bucket", tiles.alias("tiles")), "hot")
    few = hot.count()
    if not few:
        return rows
    held = F.broadcast(hot) if few <= 100_000 else hot  # two numbers a bucket
    own = F.pmod(F.xxhash64(by), F.col("tiles")).cast("int")
    pair = F.transform(F.sequence(F.lit(0), F.col("tiles") - 1), lambda j: F.xxhash64(F.col("bucket"), F.least(own, j), F.greatest(own, j)))
    to = F.when(F.col("tiles").isNull(), F.array("bucket")).when(F.col("tiles") > 0, pair).otherwise(F.array().cast("array<bigint>"))
    rest = [c for c in rows.columns if c != "bucket"]
    return rows.join(held, "bucket", "left").select(F.explode(to).alias("bucket"), *rest)


def fingerprint_classes(prints: DataFrame, tau: int = 4) -> DataFrame:
    """(fp, root) for the distinct fingerprints that have a link; prints holds distinct fingerprints."""
    n, both = bit_statistics(prints)
    if n < 2:
        return prints.select("fp", F.col("fp").alias("root")).limit(0)
    plan = plan_groups(n, both, tau)
    rows = staged(probes(prints, plan), "probes")
    dealt = cut_hot(rows).repartition("bucket").sortWithinPartitions("bucket")
    return components(links(dealt, tau)).select(F.col("node").alias("fp"), "root")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", tau: int = 4) -> DataFrame:
    """One row a document: ``id_col``, fp, component_id (least identifier reachable by links, itself included).

    Documents of equal fingerprint are linked; so are fingerprints at most ``tau`` bits apart. Null and blank texts have
    fingerprint zero and are linked like any other. Repeated rows stay. Null identifiers are never the least; a
    component that has no other gets null. An empty table gives an empty one. Other columns are not read.
    """
    spark = docs.sparkSession
    ship(spark)
    own = docs.select(F.col(f"`{id_col}`").alias("doc"), F.col(f"`{text_col}`").alias("text"))
    own = staged(with_fingerprints(own, "text", "fp", ["doc"]), "prints")
    prints = staged(own.groupBy("fp").agg(F.min("doc").alias("least"), F.count("*").alias("n")), "distinct")
    classes = fingerprint_classes(prints, tau)
    whole = prints.join(classes, "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    least = whole.groupBy("root").agg(F.min("least").alias("component_id"))
    named = staged(whole.join(least, "root").select("fp", "component_id", "n"), "components")
    return join_hot(own, named, "fp", "n").select(F.col("doc").alias(id_col), "fp", "component_id")


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", tau: int = 4) -> DataFrame:
    """``docs`` with one document of each group of near-duplicates: that of the least identifier (nulls last), then
    the least fingerprint and hash of text; whole rows and columns as they were.

    Rows get a number when they are staged with their fingerprints. The choice is made on narrow rows; whole ones move
    once, to meet the chosen numbers.
    """
    fp, rid, h = (free(docs, n) for n in ("_fp", "_rid", "_h"))
    numbered = with_fingerprints(docs, text_col, fp).withColumn(rid, F.monotonically_increasing_id())
    own = staged(numbered.withColumn(h, F.xxhash64(f"`{text_col}`")), "prints")
    key = F.col(f"`{id_col}`")
    who = F.struct(key.isNull().alias("none"), key.alias("doc"), F.col(fp).alias("fp"), F.col(h).alias("h"), F.col(rid).alias("rid"))
    prints = staged(own.groupBy(F.col(fp).alias("fp")).agg(F.min(who).alias("least")), "distinct")
    classes = fingerprint_classes(prints, tau)
    whole = prints.join(classes, "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    chosen = whole.groupBy("root").agg(F.min("least").alias("least")).select(F.col("least.rid").alias(rid))
    return own.join(chosen, rid, "left_semi").select(*(F.col(f"`{c}`") for c in docs.columns))


def op7(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    found = near_duplicates(docs)
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")

"""SimHash near-duplicates of whole texts at a Jaccard similarity of word shingles: candidates by fingerprints, then an
exact check.

Texts of equal shingle sets are one class. A class has a SimHash of 128 bits; those within ``TAU`` bits of one another
are found by the generalised pigeonhole of ``simhash``, all of them. What meets is decided by the similarity of the whole
shingle sets, so nothing below the threshold is ever linked. At a similarity of exactly 0.8 two fingerprints differ in
19.4 bits on average (deviation 4.1), and within ``TAU`` in 98.7 of 100 cases; at 0.85 in all but one of a thousand.

Classes are dealt into tiles, and each pair of tiles is a task's work, in which tables of the values of every group of
bits are probed. So a row is moved once for each tile, and each pair of classes meets in one task.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from fractions import Fraction
from functools import lru_cache
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import annotate, free, ship, staged, texts
from .components import components, unite
from .simhash import Plan, bit_statistics, plan_groups, signed, typed

#: Words of a fingerprint, and the differing bits that candidates may have.
WORDS = ("w0", "w1")
TAU = 28
#: Numbers of groups that are weighed.
GROUPS = (4, 5, 6, 7, 8, 9, 10, 12, 14, 16)
#: Rows that a task gathers, at least, before it works on whole buckets; classes of a tile, at most; tiles, at least.
BLOCK, ROWS, TILES = 65_536, 400_000, 8
#: What a probe of a table costs, in comparisons of two fingerprints.
PROBE = 1.5
#: Differing bits up to which two classes are likely to be similar enough (the mean at a similarity of 0.8).
LIKELY = 19
#: Rows up to which a table of identifiers is broadcast; texts of a tile of them, and pairs held at once.
FEW, TILE, HELD = 1_000_000, 512, 2_000_000


def shingles(text: str, words: int = 5, seed: int = 42) -> np.ndarray:
    """Sorted distinct hashes of the word shingles; a shorter text is one shingle, a blank one has none."""
    parts = text.encode("utf-8", "surrogatepass").lower().split()  # bytes: A-Z and ASCII blanks alone
    if not parts:
        return np.zeros(0, np.uint64)
    joined = b" ".join(parts)
    ends = np.cumsum(np.fromiter(map(len, parts), np.int64, len(parts)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    words = min(words, len(parts))
    hashed = xxhash.xxh64_intdigest
    pairs = zip(starts[: len(parts) - words + 1].tolist(), ends[words - 1 :].tolist(), strict=True)
    return np.unique(np.fromiter((hashed(joined[x:y], seed) for x, y in pairs), np.uint64))


def class_key(own: np.ndarray) -> int:
    return signed(xxhash.xxh64_intdigest(own.tobytes(), 7)) if len(own) else 0


#: Bits of a byte, the greatest first; and where the counts of each byte of a fingerprint begin.
BYTE = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1).astype(np.float64)
OFFSETS = np.arange(8 * len(WORDS)) * 256


def prints_of(own: np.ndarray) -> list[int]:
    """The fingerprint as signed words: the majority bits of the hashes, and of a remix of them for each further word."""
    total = np.zeros(len(OFFSETS) * 256)
    for at in range(0, len(own), 1 << 14):
        part = own[at : at + (1 << 14)]
        mixed = np.empty((len(part), len(WORDS)), ">u8")
        for k in range(len(WORDS)):
            h = part
            if k:
                h = part + np.uint64(k * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
                h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
                h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
                h = h ^ (h >> np.uint64(31))
            mixed[:, k] = h
        total += np.bincount((mixed.view(np.uint8).reshape(len(part), -1) + OFFSETS).ravel(), minlength=len(total))
    ones = total.reshape(-1, 256) @ BYTE  # how often each bit of each byte is set
    packed = np.packbits(2 * ones > len(own), axis=1).ravel().tobytes()
    return [signed(int.from_bytes(packed[8 * k : 8 * k + 8], "big")) for k in range(len(WORDS))]


def tiles_of(n: int) -> int:
    return max(TILES, math.ceil(n / ROWS))


def plan_of(n: int, chances: np.ndarray) -> Plan:
    """Groups of bits and thresholds that suit the tiles of n classes; ``chances`` that each two bits are both set."""
    size = math.ceil(n / tiles_of(n))
    return plan_groups(size, chances * size, TAU, PROBE, GROUPS)


@lru_cache(maxsize=64)
def masks(width: int, most: int) -> np.ndarray:
    """Values of ``width`` bits with at most ``most`` set, fewest first."""
    return np.array([sum(1 << k for k in c) for r in range(most + 1) for c in combinations(range(width), r)], np.int64)


def values(x: list[np.ndarray], bits: tuple[int, ...]) -> np.ndarray:
    out = np.zeros(len(x[0]), np.int64)
    for k, b in enumerate(bits):
        out |= ((x[b // 64] >> np.uint64(b % 64)) & np.uint64(1)).astype(np.int64) << k
    return out


def dealt(classes: DataFrame, n: int) -> DataFrame:
    """Every row once for each pair of tiles that its own is in (bucket). side: 0 and 1 for the first and the second tile
    of a pair, 2 in the pair of a tile with itself."""
    k = tiles_of(n)
    own = classes.withColumn("own", F.pmod(F.xxhash64("key"), F.lit(k)))
    own = own.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(k - 1))))
    side = F.when(F.col("own") == F.col("other"), 2).when(F.col("own") < F.col("other"), 0).otherwise(1)
    return own.withColumn("bucket", F.least("own", "other") * k + F.greatest("own", "other")).withColumn("side", side).drop("own", "other")


class Met:
    """The pairs of classes that meet in a bucket: of one tile, or of one of the first with one of the second."""

    def __init__(self, side, key, words, plan: Plan):
        self.key, self.words, self.plan = key, [w.view(np.uint64) for w in words], plan
        self.inner = bool((side == 2).any())
        self.filed, self.asking = np.flatnonzero(side != 1), np.flatnonzero(side != 0)

    def pairs(self) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """(rows, partners, differing bits), each pair once, in the first group of bits in which it meets."""
        rank = np.zeros(len(self.key), np.int64)
        for group, (bits, limit) in enumerate(zip(self.plan.groups, self.plan.limits, strict=True)):
            if limit < 0:
                continue
            value = values(self.words, bits)
            own = self.filed[np.argsort(value[self.filed], kind="stable")]
            first = np.searchsorted(value[own], np.arange((1 << len(bits)) + 1))  # of every value
            rank[own] = np.arange(1, len(own) + 1)
            for m in masks(len(bits), limit).tolist():
                ask, target = self.asking, value[self.asking] ^ m
                if self.inner and m:  # the lesser value probes the greater one
                    up = target > value[ask]
                    ask, target = ask[up], target[up]
                at = first[target]
                if self.inner and not m:
                    at = np.maximum(at, rank[ask])
                yield from self._expand(own, ask, at, first[target + 1], group)

    def _expand(self, own, ask, at, end, group: int):
        """Partners from ``at`` to ``end`` of each row, about a million at a time."""
        some = np.flatnonzero(end > at)
        ask, at, width = ask[some], at[some], (end - at)[some]
        total = np.cumsum(width)
        s = 0
        while s < len(ask):
            e = max(s + 1, int(np.searchsorted(total, (total[s - 1] if s else 0) + (1 << 20), "right")))
            n = width[s:e]
            p = np.repeat(ask[s:e], n)
            f = own[np.repeat(at[s:e], n) + np.arange(len(p)) - np.repeat(np.cumsum(n) - n, n)]
            apart = sum(np.bitwise_count(w[p] ^ w[f]).astype(np.int64) for w in self.words)
            ok = np.flatnonzero(apart <= TAU)
            if len(ok):
                ok = ok[first_met(self.words, p[ok], f[ok], self.plan, group)]
                yield p[ok], f[ok], apart[ok]
            s = e

    def held(self) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]] | list:
        """The pairs, to be gone over again: in memory if they are few."""
        kept, size = [], 0
        for part in self.pairs():
            kept.append(part)
            size += len(part[0])
            if size > HELD:
                return Again(self)
        return kept

    def chosen(self) -> tuple[np.ndarray, ...]:
        """Of each row with partners: the row, its nearest partner and by how many bits it differs, the partner that is
        near to most (which in a group of copies is what they were made from) and to how many, the number of partners."""
        size = len(self.key)
        near, count = np.zeros(size, np.int64), np.zeros(size, np.int64)
        best, hub = np.full(size, 1 << 60, np.int64), np.full(size, -1, np.int64)
        pairs = self.held()
        for p, f, apart in pairs:
            for x, y in ((p, f), (f, p)):
                np.minimum.at(best, x, apart << 32 | y)
                near += np.bincount(x[apart <= LIKELY], minlength=size)
                count += np.bincount(x, minlength=size)
        for p, f, _ in pairs:
            for x, y in ((p, f), (f, p)):
                np.maximum.at(hub, x, near[y] << 32 | (size - y))  # of equals the first
        a = np.flatnonzero(count)
        return a, best[a] & 0xFFFFFFFF, best[a] >> 32, size - (hub[a] & 0xFFFFFFFF), hub[a] >> 32, count[a]


class Again:
    def __init__(self, met: Met):
        self.met = met

    def __iter__(self):
        return self.met.pairs()


def by_bucket(rows: DataFrame, work, names: list[str], kinds: str) -> DataFrame:
    """Apply ``work`` to the columns of whole buckets, sorted by bucket and key, of one partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list[np.ndarray]] = []
        size = 0
        for batch in batches:
            held.append([c.to_numpy() for c in batch.columns[: len(names)]])
            size += batch.num_rows
            if held[0][0][0] == held[-1][0][-1] or size < BLOCK:  # the bucket goes on, or there is little to do yet
                continue
            whole = [np.concatenate(c) for c in zip(*held, strict=True)]
            cut = int(np.flatnonzero(whole[0] != whole[0][-1])[-1]) + 1
            yield from parts(*(c[:cut] for c in whole))
            held, size = [[c[cut:] for c in whole]], len(whole[0]) - cut
        if held:
            yield from parts(*(np.concatenate(c) for c in zip(*held, strict=True)))

    def parts(*whole):
        starts = np.concatenate(([0], np.flatnonzero(whole[0][1:] != whole[0][:-1]) + 1, [len(whole[0])]))
        for k in np.flatnonzero(np.diff(starts) > 1).tolist():
            for made in work(*(c[starts[k] : starts[k + 1]] for c in whole)):
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in made], names=columns)

    columns = [k.split()[0] for k in kinds.split(", ")]
    dealt = rows.select(*names).repartition("bucket").sortWithinPartitions("bucket", "key")
    return dealt.mapInArrow(typed(run, kinds), kinds)


def partners(classes: DataFrame, plan: Plan, n: int) -> DataFrame:
    """(key, partner, hub, count) of every class that the fingerprints leave partners: the nearest one, one that is near to
    many, and how many there are. A pair that is neither is of two classes with more than one partner."""

    def work(bucket, side, key, *words):
        a, partner, apart, hub, near, count = Met(side, key, words, plan).chosen()
        yield key[a], key[partner], apart, key[hub], near, count

    kinds = "key long, partner long, apart long, hub long, near long, count long"
    found = by_bucket(dealt(classes.select("key", *WORDS), n), work, ["bucket", "side", "key", *WORDS], kinds)
    nearest = F.min(F.struct("apart", "partner")).getField("partner")
    return found.groupBy("key").agg(nearest.alias("partner"), F.max(F.struct("near", "hub")).getField("hub").alias("hub"), F.sum("count").alias("count"))


def similar(x: np.ndarray, y: np.ndarray, s: Fraction) -> bool:
    if min(len(x), len(y)) * s.denominator < s.numerator * max(len(x), len(y)):
        return False
    both = len(np.intersect1d(x, y, assume_unique=True))
    return both * s.denominator >= s.numerator * (len(x) + len(y) - both)


def first_met(x: list[np.ndarray], i: np.ndarray, j: np.ndarray, plan: Plan, group: int) -> np.ndarray:
    """Whether pairs meet in no group of bits before this one."""
    ok = np.ones(len(i), bool)
    for bits, limit in zip(plan.groups[:group], plan.limits[:group], strict=True):
        if limit >= 0:
            own = [np.uint64(sum(1 << b % 64 for b in bits if b // 64 == k)) for k in range(len(x))]
            ok &= sum(np.bitwise_count((w[i] ^ w[j]) & m).astype(np.int64) for w, m in zip(x, own, strict=True)) > limit
    return ok


def unconnected(more: DataFrame, plan: Plan, n: int) -> DataFrame:
    """(a, b) that connect the classes of ``more`` (n of them, with their roots) as the pairs do that the fingerprints leave
    between different roots; of a bucket no more than it has classes."""

    def work(bucket, side, key, root, *words):
        labels, parts = np.arange(len(key)), []
        for p, f, _ in Met(side, key, words, plan).pairs():
            differ = root[p] != root[f]
            parts.append((p[differ], f[differ]))
            if sum(len(x) for x, _ in parts) > BLOCK:
                unite(labels, *(np.concatenate(c) for c in zip(*parts, strict=True)))
                parts = []
        if parts:
            unite(labels, *(np.concatenate(c) for c in zip(*parts, strict=True)))
        own = np.flatnonzero(labels != np.arange(len(key)))
        yield key[own], key[labels[own]]

    rows = dealt(more.select("key", "root", *WORDS), n)
    return by_bucket(rows, work, ["bucket", "side", "key", "root", *WORDS], "a long, b long").distinct()


def other_links(more: DataFrame, chances: np.ndarray, slim: DataFrame, words: int, s: Fraction) -> DataFrame | None:
    """Links of the pairs that were left out, between classes of different roots; none if there are no such pairs.

    ``more`` has the classes concerned, with their roots. Those that such pairs connect are a cluster. In it the classes of
    the most frequent root need no comparison with one another, only with the rest. Texts go to one task, or to one for
    each pair of tiles of a cluster, which compares fingerprints and then texts, so no pair is written.
    """
    n = more.count()
    if n < 2:
        return None
    clusters = components(unconnected(more, plan_of(n, chances), n))
    own = staged(more.join(clusters.select(F.col("node").alias("key"), F.col("root").alias("cluster")), "key"), "asked")
    if own.isEmpty():
        return None
    roots = own.groupBy("cluster", "root").agg(F.count("*").alias("n"))
    sizes = roots.groupBy("cluster").agg(F.max(F.struct("n", "root")).alias("most"), F.sum("n").alias("n"))
    rest, most = F.col("n") - F.col("most.n"), F.col("most.n")
    whole = F.col("n") <= 2 * TILE  # then all is one tile
    i, j = (F.when(whole, x).otherwise(y).cast("int") for x, y in ((1, F.ceil(rest / TILE)), (0, F.ceil(most / TILE))))
    sizes = staged(sizes.select("cluster", F.when(~whole, F.col("most.root")).alias("most"), i.alias("i"), j.alias("j")), "sizes")
    own = own.join(few(sizes), "cluster")
    major = F.coalesce(F.col("root") == F.col("most"), F.lit(False))
    tile = F.when(major, F.col("i") + F.pmod(F.xxhash64("key"), F.col("j"))).otherwise(F.pmod(F.xxhash64("key"), F.col("i"))).cast("int")
    to = F.sequence(F.lit(0), F.when(major, F.col("i")).otherwise(F.col("i") + F.col("j")) - 1)
    own = own.withColumn("tile", tile).withColumn("other", F.explode(to))
    at = ["cluster", "x", "y"]
    own = own.withColumn("x", F.least("tile", "other")).withColumn("y", F.greatest("tile", "other"))
    own = staged(own.select(*at, "tile", "key", "root", "rid", *WORDS), "again")
    rows = slim.drop("key").join(few(own), "rid").select(*at, "tile", "key", "root", *WORDS, "text")

    def run(table: pa.Table) -> pa.Table:
        key, root, tile = (table.column(c).to_numpy() for c in ("key", "root", "tile"))
        x = [table.column(w).to_numpy().view(np.uint64) for w in WORDS]
        held, text, found = {}, table.column("text"), []
        labels = np.unique(root, return_index=True, return_inverse=True)
        labels = labels[1][labels[2]]  # classes of a root are connected
        one = bool((tile == tile[0]).all()) if len(tile) else True
        step = max(1, (1 << 20) // max(len(key), 1))
        for k in range(0, len(key), step):
            i = np.arange(k, min(k + step, len(key)))
            apart = sum(np.bitwise_count(w[i, None] ^ w[None, :]).astype(np.int16) for w in x)
            ok = (apart <= TAU) & (root[i, None] != root[None, :]) & (i[:, None] < np.arange(len(key))[None, :])
            a, b = np.nonzero(ok if one else ok & (tile[i, None] != tile[None, :]))
            for u, v in zip(i[a].tolist(), b.tolist(), strict=True):
                if labels[u] != labels[v]:
                    for z in (u, v):
                        if z not in held:
                            held[z] = shingles(text[z].as_py() or "", words)
                    if similar(held[u], held[v], s):
                        unite(labels, np.array([u]), np.array([v]))
                        found.append((u, v))
        u, v = np.array(found, np.int64).reshape(-1, 2).T
        return pa.table({"a": key[u], "b": key[v]})

    return rows.groupBy(*at).applyInArrow(run, "a long, b long")


def verified(pairs: DataFrame, slim: DataFrame, classes: DataFrame, words: int, s: Fraction) -> DataFrame:
    """Links that connect what the pairs of classes with similarity ``s`` or more of their whole sets connect: a star to
    one class of each connected set of a task, so a task gives no more links than it holds classes.

    Pairs are dealt by the least class that their first one is paired with, which is mostly the same in a group of near
    copies; so texts move about once to where they are compared, and once for each tile of a group beyond ``TILE``.
    """
    pairs = staged(pairs, "pairs")
    both = pairs.union(pairs.select("b", "a"))
    center = both.groupBy("a").agg(F.min("b").alias("c")).select("a", F.least("a", "c").alias("g"))
    grouped = staged(pairs.join(center, "a").select("g", "a", "b"), "grouped")
    ends = grouped.select("g", F.explode(F.array("a", "b")).alias("key")).distinct()
    tiles = staged(ends.groupBy("g").agg(F.ceil(F.count("*") / TILE).cast("int").alias("tiles")), "tiles")
    rids = classes.select("key", F.col("least.rid").alias("rid"))
    ends = staged(ends.join(tiles, "g").join(rids, "key").select("g", "key", "rid", "tiles"), "ends")
    bundles = F.lit(max(1, ends.count() // TILE))
    own = lambda c: F.pmod(F.xxhash64(c), F.col("tiles")).cast("int")

    def at(x, y):
        tile = F.xxhash64(F.col("g"), F.least(x, y), F.greatest(x, y))
        return F.when(F.col("tiles") == 1, F.pmod(F.xxhash64("g"), bundles)).otherwise(tile)

    sets = slim.drop("key").join(few(ends), "rid")
    sets = sets.withColumn("at", F.explode(F.transform(F.sequence(F.lit(0), F.col("tiles") - 1), lambda j: at(own("key"), j)))).select("at", "key", "text")
    asked = grouped.join(tiles, "g").select(at(own("a"), own("b")).alias("at"), "a", "b")

    def run(asked: pa.Table, sets: pa.Table) -> pa.Table:
        keys = np.array(sets.column("key").to_pylist(), np.int64)
        held = [shingles(t or "", words) for t in sets.column("text").to_pylist()]
        by = np.argsort(keys, kind="stable")
        a, b = (by[np.searchsorted(keys, asked.column(c).to_numpy(), sorter=by)] for c in ("a", "b"))
        ok = np.zeros(len(a), bool)
        for k, (i, j) in enumerate(zip(a.tolist(), b.tolist(), strict=True)):
            ok[k] = similar(held[i], held[j], s)
        labels = np.arange(len(keys))
        unite(labels, a[ok], b[ok])
        own = np.flatnonzero(labels != np.arange(len(keys)))
        return pa.table({"a": keys[own], "b": keys[labels[own]]})

    return asked.groupBy("at").cogroup(sets.groupBy("at")).applyInArrow(run, "a long, b long")


def few(df: DataFrame) -> DataFrame:
    return F.broadcast(df) if df.count() <= FEW else df


def linked_classes(classes: DataFrame, slim: DataFrame, words: int, s: Fraction) -> DataFrame:
    """(node, root) of the classes that links of similarity ``s`` or more connect."""
    n, both = bit_statistics(classes, WORDS)
    if n < 2:
        return classes.select(F.col("key").alias("node"), F.col("key").alias("root")).limit(0)
    met = staged(partners(classes, plan_of(n, both / n), n), "met")
    pairs = met.select("key", F.col("partner").alias("p")).union(met.filter("count > 2").select("key", "hub"))
    pairs = pairs.select(F.least("key", "p").alias("a"), F.greatest("key", "p").alias("b")).distinct()
    links = staged(verified(pairs, slim, classes, words, s), "near")
    linked = components(links)
    more = met.filter("count > 1").select("key").join(classes.select("key", F.col("least.rid").alias("rid"), *WORDS), "key")
    more = more.join(linked.select(F.col("node").alias("key"), "root"), "key", "left").withColumn("root", F.coalesce("root", "key"))
    others = other_links(staged(more, "more"), both / n, slim, words, s)
    if others is None:
        return linked
    others = staged(others, "others")
    return linked if others.isEmpty() else components(links.union(others))


def keep_dissimilar(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 5, similarity: float = 0.8) -> DataFrame:
    """``docs`` with one document of each group that links of shingle similarity ``similarity`` or more connect: that of
    the least identifier (nulls last), then the least key and hash of text; whole rows and columns as they were.

    ``TAU`` is meant for similarities of 0.8 and more. Null and blank texts are alike. An empty table
    gives an empty one.
    """
    ship(docs.sparkSession)
    s = Fraction(str(similarity))
    key, rid, h, fp = (free(docs, n) for n in ("_key", "_rid", "_h", "_fp"))

    def start():
        def work(batch):
            found = [shingles(t, words) for t in texts(batch, text_col)]
            return {key: [class_key(x) for x in found], fp: [prints_of(x) for x in found]}

        return work

    fields = [T.StructField(key, T.LongType()), T.StructField(fp, T.ArrayType(T.LongType()))]
    numbered = annotate(docs, start, fields, [text_col]).withColumn(rid, F.monotonically_increasing_id())
    own = staged(numbered.withColumn(h, F.xxhash64(f"`{text_col}`")), "keys")
    slim = own.select(F.col(key).alias("key"), F.col(rid).alias("rid"), F.col(f"`{text_col}`").alias("text"))
    name = F.col(f"`{id_col}`")
    who = F.struct(name.isNull().alias("none"), name.alias("doc"), F.col(key).alias("key"), F.col(h).alias("h"), F.col(rid).alias("rid"))
    made = own.groupBy(F.col(key).alias("key")).agg(F.min(who).alias("least"), F.min(fp).alias("p"))  # equal in a class
    classes = staged(made.select("key", "least", *(F.col("p")[k].alias(c) for k, c in enumerate(WORDS))), "classes")
    linked = linked_classes(classes, slim, words, s).select(F.col("node").alias("key"), "root")
    whole = classes.join(linked, "key", "left").withColumn("root", F.coalesce("root", "key"))
    chosen = whole.groupBy("root").agg(F.min("least").alias("least")).select(F.col("least.rid").alias(rid))
    return own.join(chosen, rid, "left_semi").select(*(F.col(f"`{c}`") for c in docs.columns))

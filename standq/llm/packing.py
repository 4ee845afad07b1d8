"""Best-fit packing of token pieces into sequences, improved by swap-based local search."""

from __future__ import annotations

import zlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ship, staged
from .simhash import typed
from .tokens import public_path, tokenizer

CAPACITY = 2048
#: Pieces packed together in one task; more pieces make more groups. The search takes more than in proportion to it.
GROUP = 10_000
#: Bins that a round of the local search tries to empty.
EMPTIEST = 50
#: Rounds without an emptied bin after which the search ends.
IDLE = 3


class Reach:
    """Which bins an exchange or a move could gain in, told from sizes alone, so that no other is visited."""

    def __init__(self, bins: Bins, sizes: list[int]):
        self.bins, self.sizes, self.size = bins, sizes, np.array(sizes, np.int64)
        self.room, self.of = np.array(bins.room, np.int64), np.zeros(len(sizes), np.int64)
        self.two = np.zeros((len(bins.items), 2), np.int64)  # least and greatest sum of two items
        for b in range(len(bins.items)):
            self.update(b)

    def update(self, b: int) -> None:
        own = self.bins.items[b]
        self.of[own], self.room[b] = b, self.bins.room[b] if own else 0
        x = sorted(self.sizes[i] for i in own)
        self.two[b] = (x[0] + x[1], x[-1] + x[-2]) if len(x) > 1 else (self.bins.capacity, 0)

    def targets(self, source: int) -> list[int]:
        """By room, most first."""
        single = np.unique(self.size[self.bins.items[source]])
        own = self.size[self.bins.items[source]]
        i, j = np.triu_indices(len(own), 1)
        after = lambda sums: np.append(sums, 1 << 40)[np.searchsorted(sums, np.arange(self.bins.capacity + 1), "right")]
        room = self.room[self.of]
        ok = self.room >= single[0]
        ok[self.of[(room > 0) & (after(np.unique(np.concatenate((single, own[i] + own[j]))))[self.size] <= self.size + room)]] = True
        least, most = np.minimum(self.two, self.bins.capacity).T
        ok |= after(single)[least] <= most + self.room
        ok &= self.room > 0
        ok[source] = False
        found = np.flatnonzero(ok)
        return found[np.argsort(-self.room[found], kind="stable")].tolist()


class Bins:
    """Bins by free room, with an integer as the set of rooms in use, so the best fit is one bit operation."""

    def __init__(self, capacity: int):
        self.capacity, self.used = capacity, 0
        self.items: list[list[int]] = []
        self.room: list[int] = []
        self.by_room: dict[int, list[int]] = defaultdict(list)

    def _put(self, b: int) -> None:
        self.by_room[self.room[b]].append(b)
        self.used |= 1 << self.room[b]

    def place(self, item: int, size: int) -> None:
        """Into the bin with the least room that is enough, or a new one."""
        fits = self.used >> size
        if fits:
            room = (fits & -fits).bit_length() - 1 + size
            b = self.by_room[room].pop()
            if not self.by_room[room]:
                self.used &= ~(1 << room)
            self.items[b].append(item)
            self.room[b] = room - size
        else:
            b = len(self.items)
            self.items.append([item])
            self.room.append(self.capacity - size)
        self._put(b)


def best_fit(sizes: list[int], capacity: int) -> Bins:
    """Best-fit decreasing."""
    bins = Bins(capacity)
    for i in sorted(range(len(sizes)), key=lambda i: (-sizes[i], i)):
        bins.place(i, sizes[i])
    return bins


def improve(bins: Bins, sizes: list[int]) -> None:
    """Local search: take the emptiest bins one by one and try to spread their items over other underfull bins.

    A move puts an item where it fits; a one-for-one exchange gives a larger item for a smaller one; a two-for-one
    exchange gives one item for two. Each is made only if it raises the sum of squared fill, so what is left in the
    emptiest bin shrinks until the bin is empty. A round takes the ``EMPTIEST`` bins with most room; one that changes
    nothing, or ``IDLE`` in a row that empty none, ends the search, and so does the least number of bins that the total
    needs. Every bin with room is a partner.
    """
    cap, items, room = bins.capacity, bins.items, bins.room
    least = -(-sum(sizes) // cap)
    left = sum(1 for b in items if b)
    reach, idle = Reach(bins, sizes) if left > least else None, 0
    while left > least:
        order = sorted((b for b in range(len(items)) if items[b] and room[b]), key=lambda b: -room[b])
        emptied, gained = 0, False
        for source in order[:EMPTIEST]:
            changed = True
            while items[source] and changed:
                changed = False
                for target in reach.targets(source):
                    if not items[source]:
                        break
                    free, fill_s, fill_t = room[target], cap - room[source], cap - room[target]
                    movable = [i for i in items[source] if sizes[i] <= free]
                    if movable and fill_t + max(sizes[i] for i in movable) > fill_s - max(sizes[i] for i in movable):
                        best = max(movable, key=lambda i: sizes[i])
                        items[source].remove(best)
                        items[target].append(best)
                        room[source] += sizes[best]
                        room[target] -= sizes[best]
                        reach.update(target)
                        reach.update(source)
                        changed = True
                        continue
                    if not free:
                        continue
                    swap = best_exchange(items[source], items[target], sizes, free)
                    if swap:
                        give, take = swap
                        gain = sum(sizes[i] for i in give) - sum(sizes[i] for i in take)
                        if (fill_t + gain) ** 2 + (fill_s - gain) ** 2 > fill_t**2 + fill_s**2:
                            for i in give:
                                items[source].remove(i)
                                items[target].append(i)
                            for i in take:
                                items[target].remove(i)
                                items[source].append(i)
                            room[source] += gain
                            room[target] -= gain
                            reach.update(target)
                            reach.update(source)
                            changed = True
                gained |= changed
            emptied += not items[source]
        left -= emptied
        idle = 0 if emptied else idle + 1
        if not gained or idle == IDLE:
            return


def best_exchange(give_from: list[int], take_from: list[int], sizes: list[int], free: int) -> tuple[list[int], list[int]] | None:
    """The exchange that moves most tokens, 1 to ``free``, into the other bin: one for one, two for one or one for two."""
    best, out = 0, None
    singles = [([i], sizes[i]) for i in give_from]
    pairs = [([i, j], sizes[i] + sizes[j]) for n, i in enumerate(give_from) for j in give_from[n + 1 :]]
    takes = take_from
    for give, size in [*singles, *pairs]:
        for j in takes:
            gain = size - sizes[j]
            if best < gain <= free:
                best, out = gain, (give, [j])
    for give, size in singles:
        for n, j in enumerate(takes):
            for k in takes[n + 1 :]:
                gain = size - sizes[j] - sizes[k]
                if best < gain <= free:
                    best, out = gain, (give, [j, k])
    return out


def pack(sizes: list[int], capacity: int = CAPACITY) -> list[list[int]]:
    """Item indexes of each bin. Full-size items have bins of their own."""
    bins = best_fit(sizes, capacity)
    improve(bins, sizes)
    return [b for b in bins.items if b]


def pieces(docs: DataFrame, id_col: str, text_col: str, path: str, end_id: int, capacity: int, with_ids: bool) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 and, if asked for, ids of every piece."""
    rows = docs.select(F.col(f"`{id_col}`").alias("doc_id"), F.col(f"`{text_col}`").alias("t"))
    kinds = f"doc_id {rows.schema['doc_id'].dataType.simpleString()}, piece int, start long, length long, ids_crc32 long"
    kinds += ", ids array<int>" if with_ids else ""
    end = np.array([end_id], "<u4").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        engine = tokenizer(path)
        for batch in batches:
            out: dict[str, list] = {c.split()[0]: [] for c in kinds.split(", ")}
            for doc, raw in zip(batch.column(0).to_pylist(), engine.encode_all([t or "" for t in batch.column(1).to_pylist()]), strict=True):
                raw += end
                for piece, at in enumerate(range(0, len(raw), 4 * capacity)):
                    part = raw[at : at + 4 * capacity]
                    out["doc_id"].append(doc)
                    out["piece"].append(piece)
                    out["start"].append(at // 4)
                    out["length"].append(len(part) // 4)
                    out["ids_crc32"].append(zlib.crc32(part))
                    if with_ids:
                        out["ids"].append(np.frombuffer(part, "<u4").astype(np.int32))
            yield pa.RecordBatch.from_pydict(out)

    return rows.mapInArrow(typed(run, kinds), kinds)


def pack_documents(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    path: str | None = None,
    end_id: int = 0,
    capacity: int = CAPACITY,
    with_ids: bool = False,
    group: int = GROUP,
) -> DataFrame:
    """Pack every document into sequences of at most ``capacity`` tokens; one row a piece: id, piece, start, length,
    ids_crc32, sequence_id, offset (and ids). Only documents longer than ``capacity`` are cut.

    Full pieces are sequences of their own. All others are dealt at random into groups of about ``group`` pieces, each
    packed in a task by best fit decreasing and local search; a group leaves at most about one sequence part-filled, so
    groups cost one sequence in some ten thousand. Null and empty texts are the end id alone; repeated rows are packed
    each; an empty table gives an empty one; other columns are not read.
    """
    ship(docs.sparkSession)
    made = staged(pieces(docs, id_col, text_col, path or public_path(), end_id, capacity, with_ids), "pieces")
    full = made.filter(F.col("length") == capacity)
    rest = made.filter(F.col("length") < capacity)
    groups = max(1, -(-rest.count() // group))
    # a row's place in the staged files is random enough a deal, and repeated rows are spread by it
    slim = rest.withColumn("rid", F.monotonically_increasing_id()).withColumn("g", F.pmod(F.xxhash64("rid"), F.lit(groups)).cast("int"))

    def run(table: pa.Table) -> pa.Table:
        g = table.column("g")[0].as_py()
        order = np.argsort(table.column("rid").to_numpy(), kind="stable")
        table = table.take(pa.array(order))
        sizes = table.column("length").to_numpy()
        sequence, offset = np.zeros(len(sizes), np.int64), np.zeros(len(sizes), np.int64)
        for k, own in enumerate(pack(sizes.tolist(), capacity)):
            sequence[own] = k
            offset[own] = np.concatenate(([0], np.cumsum(sizes[own])[:-1]))
        names = [*(c for c in table.column_names if c not in ("rid", "g")), "sequence_id", "offset"]
        return pa.table([*(table.column(c) for c in names[:-2]), pa.array(sequence * groups + g), pa.array(offset)], names=names)

    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in made.schema.fields) + ", sequence_id long, offset long"
    packed = slim.groupBy("g").applyInArrow(run, kinds)
    alone = full.withColumn("sequence_id", -1 - F.monotonically_increasing_id()).withColumn("offset", F.lit(0).cast("long"))
    return packed.unionByName(alone).withColumnRenamed("doc_id", id_col)


def op4(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))


__all__ = ["best_fit", "improve", "op4", "pack", "pack_documents", "pieces"]

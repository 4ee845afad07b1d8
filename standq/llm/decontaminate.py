"""Benchmark decontamination: a broadcast hash set of normalised test n-grams against every word window.

A document's words are mapped to small numbers through the benchmark's vocabulary, so that a window can only match
where all its words are known. Windows left are looked up in the hash set by their exact word numbers, which is the
verification: equal numbers are equal words.
"""

from __future__ import annotations

import hashlib
import re
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import annotate, ship, staged, texts

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
#: Lower-cases A-Z and blanks all other ASCII outside 0-9 and a-z; bytes of non-ASCII letters stay.
TABLE = bytes(
    b + 32 if 0x41 <= b <= 0x5A else b if 0x30 <= b <= 0x39 or 0x61 <= b <= 0x7A or b >= 0x80 else 0x20 for b in range(256)
)
#: Bytes of benchmark text that one broadcast block may hold. A larger benchmark is scanned block by block.
BLOCK_BYTES = 4 << 20


def words_of(text: str) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").translate(TABLE).split()


class WindowSet:
    """All windows of a block of benchmark items, in arrays: for each length the windows as word numbers, sorted by hash,
    and the items of each. Items shorter than ``n`` words are one window of their length. Made once on the driver and
    broadcast; equal hashes are verified by the numbers."""

    def __init__(self, items: list[tuple[str, str]], n: int):
        self.vocab: dict[bytes, int] = {}
        self.items = sorted({item for item, _ in items})
        number = {item: i for i, item in enumerate(self.items)}
        found: dict[int, list[tuple[np.ndarray, int]]] = {}
        for item, text in items:
            words = words_of(text or "")
            if words:
                ids = np.array([self.vocab.setdefault(w, len(self.vocab) + 1) for w in words], np.int32)
                found.setdefault(min(n, len(words)), []).append((ids, number[item]))
        self.sizes = {}
        for size, texts_ in sorted(found.items()):
            rows = np.concatenate([np.lib.stride_tricks.sliding_window_view(ids, size) for ids, _ in texts_])
            owner = np.concatenate([np.full(len(ids) - size + 1, i, np.int32) for ids, i in texts_])
            by = np.lexsort((owner, *rows.T, mixed(rows)))
            rows, owner = rows[by], owner[by]
            same = (rows[1:] == rows[:-1]).all(axis=1)
            kept = np.concatenate(([True], ~(same & (owner[1:] == owner[:-1]))))  # an item counts once a window
            rows, owner, new = rows[kept], owner[kept], np.concatenate(([True], ~same))[kept]
            starts = np.flatnonzero(new)
            self.sizes[size] = (mixed(rows[starts]), np.ascontiguousarray(rows[starts]), np.append(starts, len(owner)), owner)

    def scan(self, words: list[bytes]) -> tuple[list[tuple[int, int]], set[str]]:
        """Merged [from, to) word intervals covered by occurring windows, and the items they belong to."""
        if not words or not self.sizes:
            return [], set()
        ids = np.fromiter(map(self.vocab.get, words, repeat(0)), np.int32, len(words))
        breaks = np.concatenate(([-1], np.flatnonzero(ids == 0), [len(ids)]))
        spans, owners = [], set()
        if np.diff(breaks).max() - 1 < min(self.sizes):
            return [], owners
        gap = np.concatenate(([0], np.cumsum(ids == 0)))
        for size, (hashes, rows, starts, owner) in self.sizes.items():
            if len(ids) < size:
                continue
            every = np.flatnonzero(gap[size:] == gap[:-size])
            for k in range(0, len(every), 1 << 16):
                at = every[k : k + (1 << 16)]
                own = ids[at[:, None] + np.arange(size)]
                h = mixed(own)
                first, last = np.searchsorted(hashes, h), np.searchsorted(hashes, h, "right")
                while (open_ := np.flatnonzero(first < last)).size:  # more than one turn only where hashes collide
                    hit = open_[(rows[first[open_]] == own[open_]).all(axis=1)]
                    spans += [(i, i + size) for i in at[hit].tolist()]
                    for w in np.unique(first[hit]).tolist():
                        owners.update(self.items[o] for o in owner[starts[w] : starts[w + 1]].tolist())
                    first[open_] += 1
        return merged(spans), owners


def mixed(rows: np.ndarray) -> np.ndarray:
    """A 64-bit hash of every row of word numbers."""
    h = np.full(len(rows), 0x9E3779B97F4A7C15, np.uint64)
    for k in range(rows.shape[1]):
        h = (h ^ rows[:, k].astype(np.uint64)) * np.uint64(0xBF58476D1CE4E5B9)
        h ^= h >> np.uint64(29)
    return h


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


INTERVALS = T.ArrayType(T.StructType([T.StructField("from_word", T.LongType()), T.StructField("to_word", T.LongType())]))
FOUND = [
    T.StructField("n_words", T.LongType()),
    T.StructField("n_hit", T.LongType()),
    T.StructField("hit_words", INTERVALS),
    T.StructField("items", T.ArrayType(T.StringType())),
    T.StructField("clean_text", T.StringType()),
]


def cut(text: str, spans: list[tuple[int, int]]) -> str:
    """The text without the words in ``spans`` and what stands between them."""
    words = list(WORD.finditer(text.translate({c: c + 32 for c in range(65, 91)})))
    out, at = [], 0
    for a, b in spans:
        out.append(text[at : words[a].start()])
        at = words[b - 1].end()
    return "".join([*out, text[at:]])


def scan(docs: DataFrame, bench: DataFrame, n: int = 10, text_col: str = "text", item_col: str = "item_id", bench_text: str = "text", with_text: bool = True, keep: list[str] | None = None, prefix: str = "") -> DataFrame:
    """Every document with n_words, n_hit, hit_words (merged word intervals), items (ids as strings, sorted as such)
    and clean_text (the text less the hit words; null without ``with_text``).

    The benchmark is measured first. Up to ``BLOCK_BYTES`` it goes out as one broadcast, a hash set in arrays; a larger one is dealt into
    blocks by hash of item, and each block scans the documents again, starting from the intervals found so far.
    Null texts have no words; empty tables give no hits; repeated items count once, those without an identifier as ``null``; columns named as new ones give way.
    """
    spark = docs.sparkSession
    ship(spark)
    bench = bench.select(F.coalesce(F.col(f"`{item_col}`").cast("string"), F.lit("null")).alias("item"), F.col(f"`{bench_text}`").alias("text"))
    size = bench.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = max(1, -(-size // BLOCK_BYTES))
    fields = [T.StructField(prefix + f.name, f.dataType) for f in FOUND]
    names = [f.name for f in FOUND]
    spans_in, items_in = prefix + "hit_words", prefix + "items"
    out, kept = docs, list(docs.columns if keep is None else keep)
    new = {f.name.lower() for f in fields}
    for b in range(blocks):
        block = bench if blocks == 1 else bench.filter(F.pmod(F.xxhash64("item", "text"), F.lit(blocks)) == b)
        held = spark.sparkContext.broadcast(WindowSet([(r.item, r.text) for r in block.collect()], n))  # of at most BLOCK_BYTES of text, or one item
        later = b > 0

        def start(held=held, later=later):
            windows = held.value

            def work(batch: pa.RecordBatch) -> dict[str, list]:
                made: dict[str, list] = {k: [] for k in names}
                known = zip(*(batch.column(batch.schema.get_field_index(k)).to_pylist() for k in (spans_in, items_in)), strict=True) if later else repeat(([], []))
                for text, (spans, items) in zip(texts(batch, text_col), known, strict=False):
                    words = words_of(text)
                    found, owners = windows.scan(words)
                    found = merged([*found, *((s["from_word"], s["to_word"]) for s in spans)])
                    made["n_words"].append(len(words))
                    made["n_hit"].append(sum(y - x for x, y in found))
                    made["hit_words"].append([{"from_word": x, "to_word": y} for x, y in found])
                    made["items"].append(sorted(owners | set(items)))
                    made["clean_text"].append((cut(text, found) if found else text) if with_text else None)
                return {prefix + k: v for k, v in made.items()}

            return work

        last = b == blocks - 1
        if later:
            out = staged(out, "decontaminate")
        carried = kept if last else list(dict.fromkeys([*kept, text_col]))
        out = annotate(out, start, fields, [text_col, *([spans_in, items_in] if later else [])], carried)
    return out.select(*(F.col(f"`{c}`") for c in kept if c.lower() not in new), *(F.col(f.name) for f in fields))


def decontaminate(docs: DataFrame, bench: DataFrame, mode: str = "documents", n: int = 10, text_col: str = "text") -> DataFrame:
    """Remove hit documents (``documents``) or only the hit spans (``spans``); columns stay as they were."""
    prefix, taken = "", {c.lower() for c in docs.columns}
    while any((prefix + f.name).lower() in taken for f in FOUND):
        prefix += "_"
    found = scan(docs, bench, n, text_col, with_text=mode == "spans", prefix=prefix)
    if mode == "documents":
        return found.filter(F.col(prefix + "n_hit") == 0).select(*(F.col(f"`{c}`") for c in docs.columns))
    return found.select(*(F.col(prefix + "clean_text").alias(c) if c == text_col else F.col(f"`{c}`") for c in docs.columns))


def digest(items: list[str]) -> str:
    return hashlib.sha256(",".join(items).encode()).hexdigest()


def op10(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    found = scan(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"), with_text=False, keep=["doc_id"])
    return found.select(
        "doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", "items"), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"),
    )

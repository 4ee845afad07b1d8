"""Sorted-string-table shards of token ids.

File layout (all integers little-endian unless said otherwise):

    "SQSST001" | data blocks | sparse index | Bloom filter | footer | "SQSST001"

A data block holds entries in ascending key order, each ``varint shared, varint rest, varint value bytes, rest of key,
value``: ``shared`` bytes are taken from the key before it, and every ``RESTART``-th entry shares none. Blocks are
compressed with zstd. The sparse index has one record a block: its first key, offset, stored length, tokens and entries
before it. The footer gives the places of index and filter, the counts, and a checksum of both. A look-up asks the
Bloom filter, then finds the block by binary search in the index, then scans that block alone.

Keys: null is 0x00; a long is 0x01 and eight big-endian bytes with the sign bit turned; a string is 0x02 and its UTF-8.
Byte order of keys is therefore the order of identifiers, nulls first. Values: token ids, unsigned 32-bit each.
"""

from __future__ import annotations

import bisect
import struct
import uuid
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from standq.scratch import scratch

from .common import ship
from .simhash import typed
from .tokens import public_path, tokenizer

MAGIC = b"SQSST001"
RESTART = 16
#: Shards that one task reads, one after another.
SHARDS_A_TASK = 4
FOOTER = struct.Struct("<QQQQQQI")


def key_of(doc_id: int | str | None) -> bytes:
    if doc_id is None:
        return b"\x00"
    if isinstance(doc_id, str):
        return b"\x02" + doc_id.encode()
    return b"\x01" + struct.pack(">Q", (doc_id + (1 << 63)) & ((1 << 64) - 1))


def id_of(key: bytes) -> int | str | None:
    if key[:1] == b"\x00":
        return None
    return key[1:].decode() if key[:1] == b"\x02" else struct.unpack(">Q", key[1:])[0] - (1 << 63)


def varint(n: int) -> bytes:
    out = bytearray()
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    out.append(n)
    return bytes(out)


def read_varint(data: bytes, at: int) -> tuple[int, int]:
    shift = value = 0
    while True:
        b = data[at]
        at += 1
        value |= (b & 127) << shift
        if b < 128:
            return value, at
        shift += 7


def bloom_bits(key: bytes, bits: int, hashes: int) -> list[int]:
    a, b = xxhash.xxh64_intdigest(key, 1), xxhash.xxh64_intdigest(key, 2) | 1
    return [(a + i * b) % (1 << 64) % bits for i in range(hashes)]


class ShardWriter:
    """Builds one shard in memory; entries must come in key order. Repeated keys are kept side by side."""

    def __init__(self, block_bytes: int = 64 << 10, bits_per_key: int = 10):
        self.block_bytes, self.bits_per_key = block_bytes, bits_per_key
        self.out = bytearray(MAGIC)
        self.index: list[tuple[bytes, int, int, int, int]] = []
        self.keys: list[bytes] = []
        self.tokens = 0
        self.pack = zstandard.ZstdCompressor(level=1)
        self._open()

    def _open(self) -> None:
        self.block, self.block_first, self.block_n, self.last = bytearray(), b"", 0, b""
        self.block_start = (self.tokens, len(self.keys))

    def add(self, key: bytes, value: bytes) -> None:
        shared = 0
        if self.block_n % RESTART:
            most = min(len(key), len(self.last))
            while shared < most and key[shared] == self.last[shared]:
                shared += 1
        if not self.block_n:
            self.block_first = key
        self.block += varint(shared) + varint(len(key) - shared) + varint(len(value)) + key[shared:] + value
        self.block_n += 1
        self.last = key
        self.keys.append(key)
        self.tokens += len(value) // 4
        if len(self.block) >= self.block_bytes:
            self._close_block()

    def _close_block(self) -> None:
        if self.block_n:
            stored = self.pack.compress(bytes(self.block))
            self.index.append((self.block_first, len(self.out), len(stored), *self.block_start))
            self.out += stored
        self._open()

    def finish(self) -> bytes:
        self._close_block()
        at = len(self.out)
        index = b"".join(varint(len(k)) + k + b"".join(map(varint, rest)) for k, *rest in self.index)
        bits = max(64, len(self.keys) * self.bits_per_key)
        hashes = max(1, round(self.bits_per_key * 0.69))
        field = np.zeros(bits, dtype=bool)
        for k in self.keys:
            field[bloom_bits(k, bits, hashes)] = True
        bloom = struct.pack("<QI", bits, hashes) + np.packbits(field).tobytes()
        self.out += index + bloom
        self.out += FOOTER.pack(at, len(index), at + len(index), len(bloom), len(self.keys), self.tokens, zlib.crc32(index + bloom))
        self.out += MAGIC
        return bytes(self.out)


class ShardReader:
    """Reads a shard through ``fetch(offset, size)``; at first only the footer, the index and the filter."""

    def __init__(self, data: bytes | None = None, fetch: Callable[[int, int], bytes] | None = None, size: int = 0):
        if data is not None:
            fetch, size = (lambda at, n: data[at : at + n]), len(data)
        self.fetch, self.unpack = fetch, zstandard.ZstdDecompressor()
        tail = FOOTER.size + 8
        end = fetch(max(0, size - tail), tail) if size >= tail + 8 else b""
        if end[-8:] != MAGIC or fetch(0, 8) != MAGIC:
            raise ValueError("not a shard, or cut short")
        at, n, bloom_at, bloom_n, self.n_docs, self.n_tokens, crc = FOOTER.unpack(end[:-8])
        held = fetch(at, bloom_at + bloom_n - at) if 0 <= at <= bloom_at and bloom_at + bloom_n <= size else b""
        if zlib.crc32(held) != crc:
            raise ValueError("checksum of index and filter differs")
        self.firsts: list[bytes] = []
        self.blocks: list[tuple[int, int, int, int]] = []
        place = 0
        while place < n:
            width, place = read_varint(held, place)
            self.firsts.append(held[place : place + width])
            place += width
            record = []
            for _ in range(4):
                v, place = read_varint(held, place)
                record.append(v)
            self.blocks.append(tuple(record))
        self.bits, self.hashes = struct.unpack_from("<QI", held, n)
        self.field = np.frombuffer(held, np.uint8, bloom_n - 12, n + 12)

    def block(self, i: int) -> Iterator[tuple[bytes, bytes]]:
        offset, size, _, _ = self.blocks[i]
        raw, at, key = self.unpack.decompress(self.fetch(offset, size)), 0, b""
        while at < len(raw):
            shared, at = read_varint(raw, at)
            rest, at = read_varint(raw, at)
            size, at = read_varint(raw, at)
            key = key[:shared] + raw[at : at + rest]
            at += rest
            yield key, raw[at : at + size]
            at += size

    def scan(self) -> Iterator[tuple[bytes, int, bytes]]:
        """Key, tokens of the shard before it, value."""
        for i, (_, _, before, _) in enumerate(self.blocks):
            for key, value in self.block(i):
                yield key, before, value
                before += len(value) // 4

    def may_hold(self, key: bytes) -> bool:
        return all(self.field[b >> 3] >> (7 - (b & 7)) & 1 for b in bloom_bits(key, self.bits, self.hashes))

    def get(self, key: bytes) -> list[bytes]:
        """Values of the key in stored order; none if it is absent."""
        if not self.firsts or not self.may_hold(key):
            return []
        found, i = [], max(0, bisect.bisect_left(self.firsts, key) - 1)
        while i < len(self.blocks) and self.firsts[i] <= key:
            for k, v in self.block(i):
                if k == key:
                    found.append(v)
            i += 1
        return found


def _open(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


def put(uri: str, data: bytes) -> None:
    """Write a file whole or not at all. A task that runs twice writes the same bytes under the same name."""
    target, place = _open(uri)
    folder, name = place.rsplit("/", 1)
    target.create_dir(folder, recursive=True)
    temporary = f"{folder}/.{name}-{uuid.uuid4().hex}"
    with target.open_output_stream(temporary) as f:
        f.write(data)
    try:
        target.move(temporary, place)
    except OSError:  # some file systems don't rename onto a file
        target.delete_file(temporary)
        if target.get_file_info(place).size != len(data):
            raise


MANIFEST = "path string, first_key binary, last_key binary, task int, seq int, n_docs long, n_tokens long, n_bytes long"


def write_shards(
    docs: DataFrame,
    out: str,
    id_col: str = "doc_id",
    text_col: str = "text",
    path: str | None = None,
    end_id: int = 1,
    shard_bytes: int = 16 << 20,
    n_ranges: int | None = None,
) -> DataFrame:
    """Encode every text and write shards in ascending order of ``id_col``; returns the manifest, also kept at ``out``.

    One shuffle deals rows by range of (identifier, hash of text), so even an identifier that many rows share is spread.
    A task streams its sorted rows into shards of about ``shard_bytes``, and holds one at a time. Names and bytes follow
    from the rows alone, and files appear whole, so a task that runs twice does no harm. Null
    text is empty (the end id alone), null identifiers come first, repeated rows are all kept in order of their text;
    an empty table gives an empty manifest; other columns are not read.
    """
    spark = docs.sparkSession
    ship(spark)
    path = path or public_path()
    rows = docs.select(F.col(f"`{id_col}`").alias("k"), F.col(f"`{text_col}`").alias("t")).withColumn("h", F.xxhash64("t"))
    dealt = rows.repartitionByRange(n_ranges, "k", "h") if n_ranges else rows.repartitionByRange("k", "h")
    end = np.array([end_id], "<u4").tobytes()

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        engine, writer, first, last, seq = tokenizer(path), None, b"", b"", 0
        task = TaskContext.get().partitionId()

        def close() -> pa.RecordBatch:
            data = writer.finish()
            uri = f"{out}/shards/{task:07d}-{seq:05d}.sst"
            put(uri, data)
            row = [[uri], [first], [last], [task], [seq], [len(writer.keys)], [writer.tokens], [len(data)]]
            kinds = [pa.string(), pa.binary(), pa.binary(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]
            names = [c.split()[0] for c in MANIFEST.split(", ")]
            return pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(row, kinds, strict=True)], names=names)

        for batch in batches:
            encoded = engine.encode_all([t or "" for t in batch.column(1).to_pylist()])
            for k, ids in zip(batch.column(0).to_pylist(), encoded, strict=True):
                writer = writer or ShardWriter()
                last = key_of(k)
                first = first if writer.keys else last
                writer.add(last, ids + end)
                if len(writer.out) >= shard_bytes:
                    yield close()
                    writer, seq = None, seq + 1
        if writer:
            yield close()

    made = dealt.sortWithinPartitions("k", "h", "t").mapInArrow(build, MANIFEST)
    made.repartition("path").write.mode("overwrite").parquet(f"{out}/manifest")  # few files, not one a task
    return spark.read.schema(MANIFEST).parquet(f"{out}/manifest")


def read_shards(manifest: DataFrame, schema: str, row) -> DataFrame:
    """Read the shards a manifest lists, one at a time in a task. ``row(key, start, value)`` makes an output tuple;
    ``start`` counts the tokens of all documents before it in all shards."""
    spark = manifest.sparkSession
    ship(spark)
    # tasks wrote ranges in order, and their shards in order: sums of tasks (one row each), then of the shards in a task
    before = Window.orderBy("task").rowsBetween(Window.unboundedPreceding, -1)
    tasks = manifest.groupBy("task").agg(F.sum("n_tokens").alias("all")).select("task", F.coalesce(F.sum("all").over(before), F.lit(0)).alias("start"))
    order = Window.partitionBy("task").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)
    placed = manifest.withColumn("own", F.coalesce(F.sum("n_tokens").over(order), F.lit(0))).join(tasks, "task").withColumn("base", F.col("start") + F.col("own"))
    spread = placed.select("path", "base").repartition(max(1, -(-manifest.count() // SHARDS_A_TASK)))
    columns = [c.split()[0] for c in schema.split(", ")]

    def load(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for uri, base in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                source, place = _open(uri)
                with source.open_input_stream(place) as f:
                    reader = ShardReader(f.read())
                rows = []
                for key, before, value in reader.scan():
                    rows.append(row(key, base + before, value))
                    if len(rows) == 2000:
                        yield pa.RecordBatch.from_pydict(dict(zip(columns, map(list, zip(*rows, strict=True)), strict=True)), schema=kinds)
                        rows = []
                if rows:
                    yield pa.RecordBatch.from_pydict(dict(zip(columns, map(list, zip(*rows, strict=True)), strict=True)), schema=kinds)

    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    kinds = to_arrow_schema(_parse_datatype_string(schema))
    return spread.mapInArrow(load, schema)


def read_token_table(manifest: DataFrame) -> DataFrame:
    """doc_id, start, token ids of every document in the shards (identifiers of type long)."""
    return read_shards(manifest, "doc_id long, start long, ids array<long>", lambda k, s, v: (id_of(k), s, np.frombuffer(v, "<u4").tolist()))


def lookup(manifest: DataFrame, ids: list[int]) -> list[tuple[int, list[int]]]:
    """Token ids of the documents asked for, in order of identifier; those of a repeated one in stored order.

    Shards are chosen by key range, in one job. Of a shard only the footer, index and filter are read, and of its blocks
    those that binary search names.
    """
    ship(manifest.sparkSession)
    keys = sorted({key_of(i) for i in ids})

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for uri, first, last, task, seq in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                own = keys[bisect.bisect_left(keys, first) : bisect.bisect_right(keys, last)]
                if not own:
                    continue
                source, place = _open(uri)
                with source.open_input_file(place) as f:

                    def fetch(at: int, n: int, f=f) -> bytes:
                        f.seek(at)
                        return f.read(n)

                    reader = ShardReader(fetch=fetch, size=f.size())
                    found = [(k, task, seq, n, v) for k in own for n, v in enumerate(reader.get(k))]
                if found:
                    yield pa.RecordBatch.from_pydict(dict(zip(("key", "task", "seq", "n", "value"), map(list, zip(*found, strict=True)), strict=True)))

    kinds = "key binary, task int, seq int, n int, value binary"
    made = manifest.select("path", "first_key", "last_key", "task", "seq").mapInArrow(typed(search, kinds), kinds).collect()
    made.sort(key=lambda r: (bytes(r.key), r.task, r.seq, r.n))
    return [(id_of(bytes(r.key)), np.frombuffer(bytes(r.value), "<u4").tolist()) for r in made]


def op1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The contract's digest of the written shards."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    manifest = write_shards(docs, scratch(spark))
    schema = "doc_id long, start long, n_tokens long, ids_crc32 long"
    return read_shards(manifest, schema, lambda k, s, v: (id_of(k), s, len(v) // 4, zlib.crc32(v)))


__all__ = ["ShardReader", "ShardWriter", "lookup", "op1", "read_shards", "read_token_table", "write_shards"]

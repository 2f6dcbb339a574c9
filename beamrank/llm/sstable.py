"""Token ids as sorted string tables: immutable files for look-up by document identifier.

File format, little-endian, in this order:

* blocks: entries in ascending key order. An entry is: length of the prefix it shares with the key
  before (1 byte), length of the rest (1 byte), the rest, length of the value (4 bytes), the value.
  A block begins with a whole key. A block is compressed as one zstd frame.
* index: for each block its first key (1 byte of length, then the key), offset (8), stored size (8),
  plain size (8), entries (4) and ids in it (8).
* Bloom filter: bits of all keys.
* footer of fixed size: offset and size of the index, offset and bits of the filter, number of
  hashes, bytes of an id (2 or 4), entries, ids, and the magic number.

A key is a mark (0: null identifier, 1: other) and, for the latter, the identifier plus 2^63 as 8
bytes, most significant first: keys sort as identifiers do, null first. A value is the ids with the end id.

Documents are dealt to tasks by ranges of their identifiers, from Spark's own bounded sample; rows of
one identifier are told apart by their place, so that one that very many rows share is spread too.
Each task sorts its range, encodes it and streams one file into the shared folder, under a name of its
own attempt, and reports what it wrote, with the first and last key. Only reported files are read, so
tasks that are lost or run twice leave no trace in the result. Shards stand for ``SHARD_BYTES`` of text;
beyond ``MAX_SHARDS`` of them they grow instead, as lists of files are kept by the driver.

Edge cases. A null text is empty and holds the end id alone. Repeated identifiers are separate
entries with equal keys, in any order. An empty table makes no file and an empty result. Extra
columns are not read.
"""

from __future__ import annotations

import bisect
import struct
import uuid
import zlib
from collections.abc import Iterator
from functools import reduce
from operator import or_

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from beamrank.llm import textkit
from beamrank.llm.common import durable, scratch_path
from beamrank.llm.tokens import SLICE_BYTES, encoder, vocabulary

VOCABULARY = "word_bpe_49k.json"
END_ID = 1
BLOCK_BYTES = 64 << 10
BLOOM_BITS = 10
BLOOM_HASHES = 7
#: Bytes of text that a shard should stand for.
SHARD_BYTES = 64 << 20
#: The most files of a table.
MAX_SHARDS = 20_000
MAGIC = b"BRSSTAB1"
_BLOCK = struct.Struct("<QQQIQ")
_FOOTER = struct.Struct("<QQQQIIQQ8s")


def key_of(doc_id: int | None) -> bytes:
    return b"\0" if doc_id is None else b"\1" + struct.pack(">Q", doc_id + (1 << 63))


def doc_of(key: bytes) -> int | None:
    return None if key[0] == 0 else struct.unpack(">Q", key[1:])[0] - (1 << 63)


def _bloom_places(key: bytes, bits: int, hashes: int) -> list[int]:
    a, b = zlib.crc32(key), zlib.adler32(key) ^ zlib.crc32(key[::-1], 0x5BD1E995)
    return [(a + i * (b | 1)) % bits for i in range(hashes)]


class TableWriter:
    """Writes entries that come in ascending key order."""

    def __init__(self, out, id_bytes: int, block_bytes: int = BLOCK_BYTES):
        self.out, self.id_bytes, self.block_bytes = out, id_bytes, block_bytes
        self.index, self.keys, self.place = [], [], 0
        self.entries = self.ids = 0
        self._begin()

    def _begin(self) -> None:
        self.block, self.last, self.first, self.n, self.n_ids = bytearray(), b"", None, 0, 0

    def add(self, key: bytes, value: bytes) -> None:
        """An entry; ``value`` holds ids of ``id_bytes`` each."""
        shared, both = 0, min(len(key), len(self.last))
        while shared < both and key[shared] == self.last[shared]:
            shared += 1
        self.block += struct.pack("<BB", shared, len(key) - shared) + key[shared:] + struct.pack("<I", len(value))
        self.block += value
        self.first, self.last = self.first or key, key
        self.n, self.n_ids = self.n + 1, self.n_ids + len(value) // self.id_bytes
        self.keys.append(key)
        if len(self.block) >= self.block_bytes:
            self._flush()

    def _flush(self) -> None:
        if self.n:
            data = pa.compress(self.block, codec="zstd", asbytes=True)
            self.out.write(data)
            self.index.append(bytes([len(self.first)]) + self.first + _BLOCK.pack(self.place, len(data), len(self.block), self.n, self.n_ids))
            self.place += len(data)
            self.entries, self.ids = self.entries + self.n, self.ids + self.n_ids
        self._begin()

    def close(self) -> None:
        self._flush()
        bits = max(64, len(self.keys) * BLOOM_BITS)
        bloom = np.zeros(bits, bool)
        for key in self.keys:
            bloom[_bloom_places(key, bits, BLOOM_HASHES)] = True
        index, packed = b"".join(self.index), np.packbits(bloom).tobytes()
        self.out.write(index)
        self.out.write(packed)
        self.out.write(_FOOTER.pack(self.place, len(index), self.place + len(index), bits, BLOOM_HASHES, self.id_bytes, self.entries, self.ids, MAGIC))
        self.out.close()


class TableReader:
    """Reads one file; ``source`` is a random-access file of Arrow."""

    def __init__(self, source):
        self.source = source
        source.seek(source.size() - _FOOTER.size)
        at, size, bloom_at, self.bits, self.hashes, self.id_bytes, self.entries, self.ids, magic = _FOOTER.unpack(source.read(_FOOTER.size))
        if magic != MAGIC:
            raise ValueError("not a table of this format")
        source.seek(at)
        index, self.firsts, self.blocks, i = source.read(size), [], [], 0
        while i < len(index):
            n = index[i]
            self.firsts.append(index[i + 1 : i + 1 + n])
            self.blocks.append(_BLOCK.unpack_from(index, i + 1 + n))
            i += 1 + n + _BLOCK.size
        source.seek(bloom_at)
        self.bloom = np.unpackbits(np.frombuffer(source.read((self.bits + 7) // 8), np.uint8))

    def _entries(self, block: int) -> Iterator[tuple[bytes, np.ndarray]]:
        at, size, plain, n, _ = self.blocks[block]
        self.source.seek(at)
        data, i, key = pa.decompress(self.source.read(size), plain, codec="zstd", asbytes=True), 0, b""
        for _ in range(n):
            shared, rest = data[i], data[i + 1]
            key = key[:shared] + data[i + 2 : i + 2 + rest]
            i += 2 + rest
            (size,) = struct.unpack_from("<I", data, i)
            yield key, np.frombuffer(data, f"<u{self.id_bytes}", size // self.id_bytes, i + 4)
            i += 4 + size

    def scan(self) -> Iterator[tuple[bytes, np.ndarray]]:
        for block in range(len(self.blocks)):
            yield from self._entries(block)

    def get(self, doc_id: int | None) -> list[np.ndarray]:
        """The values of all entries with this identifier."""
        key = key_of(doc_id)
        if not self.entries or not self.bloom[_bloom_places(key, self.bits, self.hashes)].all():
            return []
        found = []
        for block in range(max(0, bisect.bisect_left(self.firsts, key) - 1), len(self.blocks)):
            if self.firsts[block] > key:
                break
            found += [ids for k, ids in self._entries(block) if k == key]
        return found


def open_table(path: str) -> TableReader:
    store, place = fs.FileSystem.from_uri(path)
    return TableReader(store.open_input_file(place))


def _shards(docs: DataFrame, shard_bytes: int) -> int:
    """How many files the bytes of text ask for."""
    n, size = docs.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).head()
    least = min(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), n // 500)
    return min(MAX_SHARDS, max(1, least, -(-int(size) // shard_bytes)))


def write_tables(docs: DataFrame, folder: str, end_id: int = END_ID, vocabulary_path: str | None = None, shard_bytes: int = SHARD_BYTES) -> DataFrame:
    """Encode and write all documents. Returns the files in order of their keys: shard, path, entries, ids, first, last (a stored table)."""
    path = vocabulary_path or vocabulary(VOCABULARY)

    def write(batches):
        code, writer = encoder(path), None
        narrow = np.dtype("<u2") if code.tokenizer.get_vocab_size() <= 1 << 16 else np.dtype("<u4")
        shard = TaskContext.get().partitionId()
        name = f"shard-{shard:06d}-{uuid.uuid4().hex[:12]}.sst"
        store, place = fs.FileSystem.from_uri(folder)
        for batch in batches:
            for part in textkit.slices(batch, "text", SLICE_BYTES):
                ids, at = code.encode(part.column(1))
                values = memoryview(np.insert(ids, at[1:], end_id).astype(narrow)).cast("B")
                edges = ((at + np.arange(len(at))) * narrow.itemsize).tolist()
                writer = writer or TableWriter(store.open_output_stream(f"{place}/{name}"), narrow.itemsize)
                for doc, a, b in zip(part.column(0).to_pylist(), edges, edges[1:], strict=False):
                    writer.add(key_of(doc), values[a:b])
        if writer:
            writer.close()
            yield pa.record_batch([[shard], [f"{folder}/{name}"], [writer.entries], [writer.ids], [writer.keys[0]], [writer.keys[-1]]], schema=_manifest)

    store, place = fs.FileSystem.from_uri(folder)
    store.create_dir(place, recursive=True)
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text", F.monotonically_increasing_id().alias("row_no"))
    dealt = rows.repartitionByRange(_shards(docs, shard_bytes), "doc_id", "row_no").sortWithinPartitions("doc_id")
    return durable(dealt.select("doc_id", "text").mapInArrow(write, "shard int, path string, entries bigint, ids bigint, first binary, last binary"), "files")


_manifest = pa.schema([("shard", pa.int32()), ("path", pa.string()), ("entries", pa.int64()), ("ids", pa.int64()), ("first", pa.binary()), ("last", pa.binary())])


def read_tables(files: DataFrame) -> DataFrame:
    """All entries of the files: doc_id, start (ids of all documents before it), ids."""
    return _read(files, "ids array<int>", lambda ids: ids.astype(np.int32), pa.list_(pa.int32()))


def read_digests(files: DataFrame) -> DataFrame:
    """As ``read_tables``, with n_tokens and ids_crc32 in place of the ids."""
    return _read(files, "ids_crc32 bigint", lambda ids: zlib.crc32(ids.astype("<u4").tobytes()), pa.int64())


def _read(files: DataFrame, column: str, value, kind: pa.DataType) -> DataFrame:
    before = Window.partitionBy(F.lit(0)).orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    starts = files.withColumn("first", F.coalesce(F.sum("ids").over(before), F.lit(0))).select("path", "first")

    def read(batches):
        for batch in batches:
            for path, start in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                docs, starts, sizes, values = [], [], [], []
                for key, ids in open_table(path).scan():
                    docs.append(doc_of(key))
                    starts.append(start)
                    sizes.append(len(ids))
                    values.append(value(ids))
                    start += len(ids)
                    if len(docs) == 1000:
                        yield _batch(docs, starts, sizes, values, kind)
                        docs, starts, sizes, values = [], [], [], []
                if docs:
                    yield _batch(docs, starts, sizes, values, kind)

    spread = starts.repartition(files.sparkSession.sparkContext.defaultParallelism * 4, "path")
    return spread.mapInArrow(read, f"doc_id bigint, start bigint, n_tokens bigint, {column}")


def _batch(docs, starts, sizes, values, kind) -> pa.RecordBatch:
    return pa.record_batch([pa.array(docs, pa.int64()), pa.array(starts, pa.int64()), pa.array(sizes, pa.int64()), pa.array(values, kind)], ["doc_id", "start", "n_tokens", "ids_crc32" if kind == pa.int64() else "ids"])


def lookup(files: DataFrame, doc_ids: list[int]) -> dict[int, list[list[int]]]:
    """Ids of a few documents: only files whose keys enclose one of them are opened, then their filters and indexes."""
    found: dict[int, list[list[int]]] = {}
    keys = {doc: key_of(doc) for doc in doc_ids}
    if not keys:
        return found
    enclosed = reduce(or_, [(F.col("first") <= F.lit(k)) & (F.col("last") >= F.lit(k)) for k in keys.values()])
    for row in files.where(enclosed).select("path", "first", "last").toLocalIterator():
        table = open_table(row["path"])
        for doc, key in keys.items():
            if row["first"] <= key <= row["last"] and (hits := table.get(doc)):
                found.setdefault(doc, []).extend(ids.tolist() for ids in hits)
    return found


def encode_to_tables(spark: SparkSession, docs: DataFrame, end_id: int = END_ID, vocabulary_path: str | None = None, shard_bytes: int = SHARD_BYTES) -> DataFrame:
    """Write tables into the shared folder, and read their digests back."""
    return read_digests(write_tables(docs, scratch_path(spark, "tables"), end_id, vocabulary_path, shard_bytes))

"""Token ids in sorted-string-table shards.

A shard file holds the documents of one range of ids, in ascending order:

    data block ...   entries: shared key bytes, other key bytes, value bytes (varints), key rest, value; every
                     ``RESTART``-th key is whole, and the places of whole keys end the block; blocks are zstd-compressed
                     and followed by their crc32
    Bloom filter     ``BLOOM_BITS`` bits for each key, ``BLOOM_HASHES`` probes
    block index      last key, offset and size of each block (sparse: one entry a block)
    footer           places of both, counts, magic; fixed size, at the end

A key is a byte that tells null from a number, and the number's eight bytes with the sign bit turned, so that bytes sort
as numbers do. A value is a byte for the width of an id (2 or 4) and the ids, little-endian. A lookup reads the footer,
asks the filter, finds the block by binary search in the index and the key by binary search over whole keys in the block.

Documents are encoded where they are read, and only compact ids move: they are dealt to shards by bounds taken from the
doc_id column, sorted there, and written by the task that holds them, under a name of its own, to the shared folder; the
table of shards lists the files of tasks that ended well. A shard is a task of its own (its number is the partition, not
hashed, so no two shards meet in one task). Beyond ``MOST_SHARDS`` of them shards get larger instead of more, which bounds
tasks, bounds and the quantile sketch on the driver.

Defined cases: null text is an empty text, whose ids are the end id alone; documents with null doc_id come first; rows that
repeat a doc_id are kept, ordered by their ids' crc32; an empty table gives no shards and an empty result.
"""

from __future__ import annotations

import struct
import uuid
import zlib
from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyarrow import fs as arrow_fs
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from taskmesh.llm.encode import BYTE_BPE, encoder
from taskmesh.llm.words import lean, text_bytes
from taskmesh.sources import load, materialise, shared_dir

BLOCK_BYTES = 64 << 10
RESTART = 16
BLOOM_BITS = 10
BLOOM_HASHES = 7
MAGIC = b"TMSST01\n"
_FOOTER = struct.Struct("<QQQQQQ8s")
DOCS_PER_SHARD = 8192
MOST_SHARDS = 32_768
END = 0


def key_bytes(doc_id: int | None) -> bytes:
    return b"\x00" if doc_id is None else b"\x01" + struct.pack(">Q", (doc_id + (1 << 63)) & ((1 << 64) - 1))


def key_number(key: bytes) -> int | None:
    return None if key == b"\x00" else struct.unpack(">Q", key[1:])[0] - (1 << 63)


def value_bytes(ids: bytes) -> bytes:
    """ids as 32-bit bytes, stored in 16 bits each where all of them fit."""
    numbers = np.frombuffer(ids, "<u4")
    return b"\x02" + numbers.astype("<u2").tobytes() if not len(numbers) or numbers.max() < 65536 else b"\x04" + ids


def value_ids(value: bytes) -> np.ndarray:
    return np.frombuffer(value[1:], "<u2" if value[0] == 2 else "<u4").astype("<u4")


def _varint(n: int) -> bytes:
    out = bytearray()
    while n >= 128:
        out.append(n & 127 | 128)
        n >>= 7
    out.append(n)
    return bytes(out)


def _read_varint(data: bytes, at: int) -> tuple[int, int]:
    n = shift = 0
    while True:
        c = data[at]
        at += 1
        n |= (c & 127) << shift
        if c < 128:
            return n, at
        shift += 7


def _probes(key: bytes, bits: int) -> list[int]:
    h = xxhash.xxh64_intdigest(key)
    low, high = h & 0xFFFFFFFF, h >> 32 | 1
    return [(low + i * high) % bits for i in range(BLOOM_HASHES)]


class ShardWriter:
    """Takes keys in ascending order and writes one shard to an open binary file."""

    def __init__(self, out) -> None:
        self.out, self.at = out, 0
        self.block, self.restarts, self.in_block, self.last = bytearray(), [], 0, b""
        self.index: list[tuple[bytes, int, int]] = []
        self.keys: list[bytes] = []
        self.tokens = 0
        self.packer = zstandard.ZstdCompressor(level=1)

    def add(self, doc_id: int | None, value: bytes) -> None:
        key = key_bytes(doc_id)
        shared = 0
        if self.in_block % RESTART:
            while shared < min(len(key), len(self.last)) and key[shared] == self.last[shared]:
                shared += 1
        else:
            self.restarts.append(len(self.block))
        self.block += _varint(shared) + _varint(len(key) - shared) + _varint(len(value)) + key[shared:] + value
        self.in_block += 1
        self.last = key
        self.keys.append(key)
        self.tokens += (len(value) - 1) // value[0]
        if len(self.block) >= BLOCK_BYTES:
            self._end_block()

    def _put(self, data: bytes) -> tuple[int, int]:
        at = self.at
        self.out.write(data)
        self.at += len(data)
        return at, len(data)

    def _end_block(self) -> None:
        if self.in_block:
            whole = bytes(self.block) + struct.pack(f"<{len(self.restarts)}I", *self.restarts) + struct.pack("<I", len(self.restarts))
            packed = self.packer.compress(whole)
            self.index.append((self.last, *self._put(packed + struct.pack("<I", zlib.crc32(packed)))))
            self.block, self.restarts, self.in_block = bytearray(), [], 0

    def close(self) -> None:
        self._end_block()
        bits = max(64, len(self.keys) * BLOOM_BITS)
        bloom = bytearray(-(-bits // 8))
        for key in self.keys:
            for p in _probes(key, bits):
                bloom[p >> 3] |= 1 << (p & 7)
        bloom_at, bloom_size = self._put(struct.pack("<Q", bits) + bytes(bloom))
        entries = b"".join(_varint(len(k)) + k + _varint(at) + _varint(size) for k, at, size in self.index)
        index_at, index_size = self._put(struct.pack("<I", len(self.index)) + entries)
        self._put(_FOOTER.pack(bloom_at, bloom_size, index_at, index_size, len(self.keys), self.tokens, MAGIC))


class ShardReader:
    """Reads a shard from a random-access file of ``size`` bytes."""

    def __init__(self, file, size: int) -> None:
        self.file = file
        bloom_at, bloom_size, index_at, index_size, self.documents, self.tokens, magic = _FOOTER.unpack(self._read(size - _FOOTER.size, _FOOTER.size))
        if magic != MAGIC:
            raise ValueError("not a shard")
        bloom = self._read(bloom_at, bloom_size)
        self.bits, self.bloom = struct.unpack("<Q", bloom[:8])[0], bloom[8:]
        data = self._read(index_at, index_size)
        (blocks,) = struct.unpack("<I", data[:4])
        at, self.index = 4, []
        for _ in range(blocks):
            n, at = _read_varint(data, at)
            key, at = data[at : at + n], at + n
            place, at = _read_varint(data, at)
            length, at = _read_varint(data, at)
            self.index.append((key, place, length))

    def _read(self, at: int, size: int) -> bytes:
        self.file.seek(at)
        return self.file.read(size)

    def _block(self, k: int) -> tuple[bytes, list[int]]:
        _, at, size = self.index[k]
        packed = self._read(at, size)
        if zlib.crc32(packed[:-4]) != struct.unpack("<I", packed[-4:])[0]:
            raise ValueError("a damaged block")
        data = zstandard.ZstdDecompressor().decompress(packed[:-4])
        (n,) = struct.unpack("<I", data[-4:])
        return data[: -4 - 4 * n], list(struct.unpack(f"<{n}I", data[-4 - 4 * n : -4]))

    @staticmethod
    def _entries(data: bytes, at: int = 0) -> Iterator[tuple[bytes, bytes]]:
        last = b""
        while at < len(data):
            shared, at = _read_varint(data, at)
            rest, at = _read_varint(data, at)
            size, at = _read_varint(data, at)
            last = last[:shared] + data[at : at + rest]
            at += rest
            yield last, data[at : at + size]
            at += size

    def scan(self) -> Iterator[tuple[int | None, np.ndarray]]:
        """All documents in order."""
        for k in range(len(self.index)):
            for key, value in self._entries(self._block(k)[0]):
                yield key_number(key), value_ids(value)

    def may_hold(self, doc_id: int | None) -> bool:
        return all(self.bloom[p >> 3] >> (p & 7) & 1 for p in _probes(key_bytes(doc_id), self.bits))

    def get(self, doc_id: int | None) -> list[np.ndarray]:
        """ids of every row with this doc_id."""
        key = key_bytes(doc_id)
        if not self.may_hold(doc_id):
            return []
        found = []
        k = bisect_left([last for last, _, _ in self.index], key)
        while k < len(self.index):
            data, whole = self._block(k)
            heads = [next(self._entries(data, at))[0] for at in whole]
            start = max(0, bisect_left(heads, key) - 1)
            for own, value in self._entries(data, whole[start]):
                if own == key:
                    found.append(value_ids(value))
                elif own > key:
                    return found
            k += 1
        return found


def open_shard(uri: str) -> ShardReader:
    files, path = arrow_fs.FileSystem.from_uri(uri)
    file = files.open_input_file(path)
    return ShardReader(file, file.size())


def write_shards(docs: DataFrame, folder: str, tokenizer: tuple[str, bool] = BYTE_BPE, end: int = END, docs_per_shard: int = DOCS_PER_SHARD, most_shards: int = MOST_SHARDS) -> DataFrame:
    """docs: doc_id, text. Writes the shards into ``folder`` (a URI every executor reaches) and returns their stored table:
    shard (in order of doc_id), path, documents, tokens."""
    docs = docs.select("doc_id", "text")
    ids_only = docs.select("doc_id")
    shards = max(1, min(most_shards, -(-ids_only.count() // docs_per_shard)))
    bounds = sorted(set(ids_only.stat.approxQuantile("doc_id", [k / shards for k in range(1, shards)], 0.25 / shards))) if shards > 1 else []
    shared = docs.sparkSession.sparkContext.broadcast(np.array(bounds, np.float64))
    tail = np.array([end], "<u4").tobytes()

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(*tokenizer)
        for b in batches:
            ids = [i + tail for i in enc.encode(text_bytes(b))]
            numbers = b.column("doc_id").fill_null(-(1 << 63)).to_numpy(zero_copy_only=False).astype(np.float64)
            shard = np.searchsorted(shared.value, numbers, "left")
            yield pa.RecordBatch.from_arrays(
                [pa.array(shard, pa.int32()), b.column("doc_id"), pa.array([zlib.crc32(i) for i in ids], pa.int64()), pa.array([value_bytes(i) for i in ids], pa.binary())],
                ["shard", "doc_id", "crc", "value"],
            )

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        files, path = arrow_fs.FileSystem.from_uri(folder)
        files.create_dir(path, recursive=True)
        now = writer = out = name = None
        done = []

        def finish() -> None:
            writer.close()
            out.close()
            done.append((now, f"{folder}/{name}", len(writer.keys), writer.tokens))

        for b in batches:
            for shard, doc_id, value in zip(b.column("shard").to_pylist(), b.column("doc_id").to_pylist(), b.column("value").to_pylist(), strict=True):
                if shard != now:
                    if writer:
                        finish()
                    now, name = shard, f"shard-{shard:07d}-{uuid.uuid4().hex[:8]}.sst"
                    out = files.open_output_stream(f"{path}/{name}")
                    writer = ShardWriter(out)
                writer.add(doc_id, value)
        if writer:
            finish()
        columns = list(zip(*done, strict=True)) or [[], [], [], []]
        yield pa.RecordBatch.from_arrays(
            [pa.array(columns[0], pa.int32()), pa.array(columns[1], pa.string()), pa.array(columns[2], pa.int64()), pa.array(columns[3], pa.int64())], ["shard", "path", "documents", "tokens"]
        )

    encoded = docs.mapInArrow(lean(encode, keeps=True), "shard int, doc_id long, crc long, value binary")
    sorted_ = encoded.repartitionById(len(bounds) + 1, F.col("shard")).sortWithinPartitions("shard", F.col("doc_id").asc_nulls_first(), "crc")
    return materialise(sorted_.mapInArrow(write, "shard int, path string, documents long, tokens long"), "sst-shards")


def read_shards(shards: DataFrame) -> DataFrame:
    """Every document of the shards: doc_id, start (ids of all documents before it), n_tokens, ids_crc32; ids come from the files."""
    placed = shards.select("shard", "path", (F.sum("tokens").over(Window.orderBy("shard")) - F.col("tokens")).alias("base"))

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for path, base in zip(b.column("path").to_pylist(), b.column("base").to_pylist(), strict=True):
                doc_ids, starts, sizes, marks = [], [], [], []
                for doc_id, ids in open_shard(path).scan():
                    doc_ids.append(doc_id), starts.append(base), sizes.append(len(ids)), marks.append(zlib.crc32(ids.tobytes()))
                    base += len(ids)
                yield pa.RecordBatch.from_arrays([pa.array(v, pa.int64()) for v in (doc_ids, starts, sizes, marks)], ["doc_id", "start", "n_tokens", "ids_crc32"])

    width = max(1, shards.count())
    return placed.repartitionById(width, F.col("shard")).mapInArrow(read, "doc_id long, start long, n_tokens long, ids_crc32 long")


def lookup(shards: DataFrame, doc_id: int | None) -> list[np.ndarray]:
    """ids of one document, by the shards whose filter may hold it (paths only come to the driver, one a shard)."""
    return [ids for r in shards.orderBy("shard").select("path").toLocalIterator() for ids in open_shard(r.path).get(doc_id)]


def op4_sstable(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents", ["doc_id", "text"])
    return read_shards(write_shards(docs, f"{shared_dir(spark)}/sst-{uuid.uuid4().hex[:8]}"))

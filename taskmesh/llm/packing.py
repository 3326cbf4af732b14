"""Packing documents into sequences by best-two-fit.

A bin is filled greedily: the longest piece left, then again and again the longest that fits. Then its smallest piece is
taken out if two unpacked pieces together fill the widened gap more tightly, as long as that gains. Only lengths matter
for this, so the plan is made on counts by length: at most ``capacity`` numbers, whatever the corpus, reach the driver. A
filled bin is a pattern of lengths that repeats as often as the counts allow, so the plan's size is bounded by lengths too.

The pieces then take places: those of one length are ranked, by chunk so that no length is sorted in one task, and a
piece's rank falls into one run of one pattern, which names its sequence and its offset there.

Defined cases: null text is an empty text, whose piece is the end id alone; only documents longer than ``capacity`` are
cut, and their last piece may be shorter; rows that repeat are packed one by one; a null doc_id is packed as any other; an
empty table gives an empty result.
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from taskmesh.llm.encode import WORD_BPE, encoder
from taskmesh.llm.words import lean, text_bytes
from taskmesh.sources import load, materialise

CAPACITY = 4096
END = 1
#: Entries of the word cache while packing, whose workers hold ids too; it bounds memory only.
PIECES = 200_000
#: Rows ranked together at most, on average.
CHUNK = 4_000


def best_two_fit(counts: np.ndarray) -> list[tuple[tuple[int, ...], int]]:
    """counts[n]: pieces of length n, up to the capacity. Returns patterns of lengths with how often each is used."""
    left = counts.astype(np.int64).copy()
    left[0] = 0
    lengths = np.arange(len(left))
    capacity = len(left) - 1
    below = np.maximum.accumulate(np.where(left > 0, lengths, 0))  # the longest length left that is at most n
    plan = []

    def take(n: int) -> None:
        left[n] -= 1
        if not left[n]:
            below[n:] = np.where(below[n:] == n, below[n - 1], below[n:])

    def put(n: int) -> None:
        left[n] += 1
        if left[n] == 1:
            below[n:] = np.maximum(below[n:], n)

    while below[capacity]:
        filled: list[int] = []
        gap = capacity
        while gap and (n := int(below[gap])):
            take(n)
            filled.append(n)
            gap -= n
        while gap:
            least = filled[-1]  # pieces come longest first
            room = gap + least
            firsts = np.flatnonzero(left[: room + 1] > 0)
            if not len(firsts):
                break
            seconds = below[np.minimum(room - firsts, firsts)]
            same = (seconds == firsts) & (left[firsts] < 2)
            seconds = np.where(same, below[np.maximum(firsts - 1, 0)], seconds)
            sums = np.where(seconds > 0, firsts + seconds, 0)
            best = int(sums.argmax())
            if sums[best] <= least:
                break
            two = int(firsts[best]), int(seconds[best])
            put(filled.pop())
            for n in two:
                take(n)
            filled = sorted([*filled, *two], reverse=True)
            gap = room - sum(two)
        used = Counter(filled)
        times = 1 + min(left[n] // c for n, c in used.items())
        for n, c in used.items():
            left[n] -= c * (times - 1)
            if not left[n] and below[n] == n:
                below[n:] = np.where(below[n:] == n, below[n - 1], below[n:])
        plan.append((tuple(filled), int(times)))
    return plan


def runs(plan: list[tuple[tuple[int, ...], int]]) -> dict[str, np.ndarray]:
    """The plan as runs of ranks: pieces of ``length`` with ranks from ``rank`` on go to sequences from ``sequence`` on, at ``offset``."""
    next_rank: Counter[int] = Counter()
    rows, sequence = [], 0
    for filled, times in plan:
        offset = 0
        for n in filled:
            rows.append((n, next_rank[n], sequence, offset))
            next_rank[n] += times
            offset += n
        sequence += times
    table = np.array(rows, np.int64).reshape(-1, 4)
    key = (table[:, 0] << 48) + table[:, 1]
    order = np.argsort(key)
    return {"key": key[order], "rank": table[order, 1], "sequence": table[order, 2], "offset": table[order, 3]}


def cut(docs: DataFrame, capacity: int = CAPACITY, tokenizer: tuple[str, bool] = WORD_BPE, end: int = END, with_ids: bool = False) -> DataFrame:
    """docs: doc_id, text. One row for each piece: doc_id, piece, start, length, ids_crc32, and its ids (little-endian, 32 bits each) if asked."""
    tail = np.array([end], "<u4").tobytes()
    schema = "doc_id long, piece int, start long, length long, ids_crc32 long" + ", ids binary" * with_ids

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(*tokenizer, entries=PIECES)
        for b in batches:
            rows: list[list] = [[], [], [], [], [], []]
            for doc_id, ids in zip(b.column("doc_id").to_pylist(), enc.encode(text_bytes(b)), strict=True):
                ids += tail
                for k, at in enumerate(range(0, len(ids), 4 * capacity)):
                    part = ids[at : at + 4 * capacity]
                    for column, value in zip(rows, (doc_id, k, at // 4, len(part) // 4, zlib.crc32(part), part if with_ids else b""), strict=True):
                        column.append(value)
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary())
            names = ["doc_id", "piece", "start", "length", "ids_crc32", "ids"][: 5 + with_ids]
            yield pa.RecordBatch.from_arrays([pa.array(v, k) for v, k, _ in zip(rows, kinds, names, strict=False)], names)

    return docs.select("doc_id", "text").mapInArrow(lean(run, keeps=True), schema)


def pack(pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """pieces: a stored table of ``cut``. The same rows with sequence_id and offset."""
    spark = pieces.sparkSession
    counts = np.zeros(capacity + 1, np.int64)
    for r in pieces.groupBy("length").count().collect():  # capacity rows at most
        counts[r.length] = r["count"]
    shared = spark.sparkContext.broadcast(runs(best_two_fit(counts)))
    chunks = max(1, -(-int(counts.sum()) // CHUNK))

    order = ["doc_id", "piece", "ids_crc32"]
    salted = pieces.withColumn("_chunk", F.pmod(F.xxhash64(*order), F.lit(chunks)))
    ahead = salted.groupBy("length", "_chunk").count()
    ahead = ahead.select("length", "_chunk", (F.sum("count").over(Window.partitionBy("length").orderBy("_chunk")) - F.col("count")).alias("_ahead"))
    ahead = ahead.withColumnsRenamed({"length": "_length", "_chunk": "_c"})
    within = F.row_number().over(Window.partitionBy("length", "_chunk").orderBy(*order)) - 1
    ranked = salted.withColumn("_rank", within).join(ahead, (F.col("length") == F.col("_length")) & (F.col("_chunk") == F.col("_c")))
    ranked = ranked.select(*pieces.columns, (F.col("_rank") + F.col("_ahead")).alias("_rank"))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        plan = shared.value
        for b in batches:
            rank = b.column("_rank").to_numpy(zero_copy_only=False)
            length = b.column("length").to_numpy(zero_copy_only=False)
            at = np.searchsorted(plan["key"], (length << 48) + rank, "right") - 1
            sequence = plan["sequence"][at] + rank - plan["rank"][at]
            kept = [c for c in b.schema.names if c != "_rank"]
            yield pa.RecordBatch.from_arrays([*[b.column(c) for c in kept], pa.array(sequence, pa.int64()), pa.array(plan["offset"][at], pa.int64())], [*kept, "sequence_id", "offset"])

    columns = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in pieces.schema)
    return ranked.mapInArrow(place, f"{columns}, sequence_id long, offset long")


def pack_documents(docs: DataFrame, capacity: int = CAPACITY, with_ids: bool = False) -> DataFrame:
    """Every piece of every document with its place."""
    return pack(materialise(cut(docs, capacity, with_ids=with_ids), "pack-pieces"), capacity)


def sequences(packed: DataFrame) -> DataFrame:
    """Packed pieces with ids put together: sequence_id, ids (bytes, at most the capacity's), and the documents in order."""
    parts = F.sort_array(F.collect_list(F.struct("offset", "doc_id", "ids")))
    return packed.groupBy("sequence_id").agg(parts.alias("parts")).select(
        "sequence_id", F.aggregate(F.col("parts.ids"), F.lit(b""), lambda a, x: F.concat(a, x)).alias("ids"), F.col("parts.doc_id").alias("doc_ids")
    )


def op6_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(load(spark, sf_dir, "documents", ["doc_id", "text"]))

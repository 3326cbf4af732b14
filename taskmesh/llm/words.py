"""Words of texts as the operators count them: A-Z lower-cased, split at ASCII white space, on UTF-8 bytes.

``bytes.lower`` and ``bytes.split`` do exactly that, and leave every other byte alone.

Also what keeps Python workers small, which live on from task to task and from operator to operator: texts are taken so many
bytes at a time (``lean``), what a worker keeps between tasks belongs to one operator at a time (``kept``), and freed memory
goes back to the system when a task ends.
"""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable, Iterator
from typing import Any

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Entries after which a worker's cache of words starts anew; it bounds memory and changes no result.
CACHE_ENTRIES = 150_000
#: Bytes of a batch that are worked on at a time, where it has several rows.
SLICE_BYTES = 4 << 20

Task = Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]
_kept: dict[Any, Any] = {}


def release() -> None:
    """Gives freed memory back to the system, as far as its library can."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def kept(key: Any, make: Callable[[], Any]) -> Any:
    """What ``make`` gave for this key, kept by the worker until another key, or a task that keeps nothing, comes."""
    if key not in _kept:
        _kept.clear()
        release()
        _kept[key] = make()
    return _kept[key]


def slices(batch: pa.RecordBatch, most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """The batch in parts of about so many bytes, a row at least, without copying."""
    parts = max(1, min(batch.num_rows, -(-batch.nbytes // most)))
    rows = max(1, -(-batch.num_rows // parts))
    for low in range(0, batch.num_rows, rows):
        yield batch.slice(low, rows)


def lean(run: Task, keeps: bool = False) -> Task:
    """A task over whole batches as one over small parts of them, which leaves little behind. keeps: it uses ``kept``."""

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if not keeps:
            _kept.clear()
        yield from run(part for b in batches for part in slices(b))
        release()

    return task


def text_bytes(batch: pa.RecordBatch, name: str | int = "text") -> list[bytes]:
    """The column as bytes; null as empty."""
    column = batch.column(name)
    return pc.fill_null(column.cast(pa.binary()), b"").to_pylist()


def words(text: bytes) -> list[bytes]:
    return text.lower().split()


def in_fold(doc_id: Column, folds: int, fold: int) -> Column:
    """Whether crc32 of doc_id as text leaves this remainder; a null doc_id does not."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % folds == fold, F.lit(False))


def numbered(df: DataFrame) -> tuple[DataFrame, list[str]]:
    """``df`` with columns c0, c1, ... and its own names, which may hold dots or clash; put them back with ``toDF``."""
    return df.toDF(*[f"c{i}" for i in range(len(df.columns))]), df.columns

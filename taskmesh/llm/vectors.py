"""What the two vector operators share: which vectors take part, and runs of equal keys in sorted Arrow batches."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def usable(vectors: DataFrame) -> DataFrame:
    """vec_id, embedding (doubles): not null, no null or non-finite component, not zero, and of the commonest length there is."""
    rows = vectors.where("vec_id IS NOT NULL AND embedding IS NOT NULL AND size(embedding) > 0").select("vec_id", F.col("embedding").cast("array<double>").alias("embedding"))
    bad = F.exists("embedding", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    some = F.exists("embedding", lambda x: x != 0)
    return rows.where(~bad & some)


def matrix(batch: pa.RecordBatch, name: str = "embedding") -> np.ndarray:
    """The column as rows of a double matrix; all of one length."""
    column = batch.column(name)
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1) if len(column) else flat.reshape(0, 0)


def by_length(batch: pa.RecordBatch, name: str = "embedding") -> Iterator[pa.RecordBatch]:
    """The batch by lengths of its vectors, in one part where they are all alike."""
    lengths = np.diff(batch.column(name).offsets.to_numpy())
    found = np.unique(lengths)
    for n in found:
        yield batch if len(found) == 1 else batch.filter(pa.array(lengths == n))


def key_runs(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[pa.RecordBatch]:
    """Batches, sorted by ``keys`` (integers), cut anew so that no run of equal keys spans two of them.

    At most one run and one batch are held; runs are bounded by whoever dealt the keys."""
    held: list[pa.RecordBatch] = []

    def key_of(b: pa.RecordBatch, row: int) -> tuple:
        return tuple(b.column(k)[row].as_py() for k in keys)

    def join(parts: list[pa.RecordBatch]) -> pa.RecordBatch:
        table = pa.Table.from_batches(parts).combine_chunks()
        return table.to_batches(max_chunksize=max(1, table.num_rows))[0]

    for b in batches:
        if not b.num_rows:
            continue
        if held and key_of(held[-1], held[-1].num_rows - 1) != key_of(b, 0):
            yield join(held)
            held = []
        columns = [b.column(k).to_numpy(zero_copy_only=False) for k in keys]
        same = np.ones(b.num_rows, bool)
        for c in columns:
            same &= c == c[-1]
        start = b.num_rows - int(np.argmin(same[::-1])) if not same.all() else 0
        if start:
            yield join([*held, b.slice(0, start)])
            held = [b.slice(start)]
        else:
            held.append(b)
    if held:
        yield join(held)


def bounds(batch: pa.RecordBatch, keys: list[str]) -> list[tuple[int, int]]:
    """Start and end of each run of equal keys."""
    change = np.zeros(batch.num_rows, bool)
    change[0] = True
    for k in keys:
        c = batch.column(k).to_numpy(zero_copy_only=False)
        change[1:] |= c[1:] != c[:-1]
    at = np.flatnonzero(change)
    return list(zip(at.tolist(), [*at[1:].tolist(), batch.num_rows], strict=True))

"""Arrow plumbing shared by the vectorised operators.

``text_chunks`` walks over record batches in slices of bounded bytes, so that a
worker's memory follows the slice and its longest text, never the batch.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa

#: Bytes of text that one slice holds at most, unless a single text is longer.
SLICE_BYTES = 1_000_000


def text_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes and row offsets of a string column; null rows are empty."""
    wide = pa.types.is_large_string(column.type)
    if column.null_count:
        column = column.fill_null("")
    offsets = np.frombuffer(column.buffers()[1], dtype=np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    if column.buffers()[2] is None:
        return np.zeros(0, dtype=np.uint8), offsets * 0
    data = np.frombuffer(column.buffers()[2], dtype=np.uint8)[offsets[0] : offsets[-1]]
    return data, offsets - offsets[0]


def _string(column: pa.Array) -> pa.Array:
    """Utf8 array of a column that may come as a null or view type."""
    if pa.types.is_string(column.type) or pa.types.is_large_string(column.type):
        return column
    return column.cast(pa.string())


def slices(batch: pa.RecordBatch, text: str, limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Slices of a batch with at most ``limit`` bytes of ``text``, one row at least."""
    if not batch.num_rows:
        return
    _, offsets = text_buffers(_string(batch.column(text)))
    start = 0
    while start < batch.num_rows:
        stop = int(np.searchsorted(offsets, offsets[start] + limit, side="right")) - 1
        stop = min(max(stop, start + 1), batch.num_rows)
        yield batch.slice(start, stop - start)
        start = stop


def text_chunks(batches: Iterable[pa.RecordBatch], text: str, limit: int = SLICE_BYTES) -> Iterator[tuple[pa.RecordBatch, pa.Array]]:
    """Pairs of a bounded slice and its text column as Utf8."""
    for batch in batches:
        for part in slices(batch, text, limit):
            yield part, _string(part.column(text))
    give_back()


def give_back() -> None:
    """Return freed memory to the system: Spark keeps idle workers, and their heaps would stay as large as they ever were."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        return

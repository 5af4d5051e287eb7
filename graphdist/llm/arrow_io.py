"""Small helpers for operators that stream Arrow batches through Python."""

from __future__ import annotations

import ctypes
import functools

import pyarrow as pa


def column_bytes(batch: pa.RecordBatch, name: str) -> list:
    """Values of a string column as bytes (None for NULL), without decoding them."""
    return batch.column(batch.schema.get_field_index(name)).cast(pa.binary()).to_pylist()


def slices(batch: pa.RecordBatch, name: str, limit: int):
    """Cut a batch so that a piece holds about ``limit`` bytes of a column: very long texts stay affordable."""
    n = batch.num_rows
    if n == 0:
        return
    col = batch.column(batch.schema.get_field_index(name))
    if col.nbytes <= limit or n == 1:
        yield batch
        return
    yield from slices(batch.slice(0, n // 2), name, limit)
    yield from slices(batch.slice(n // 2), name, limit)


def release() -> None:
    """Give freed memory back to the system: Python workers live on between tasks and stages."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def tidy(run):
    """``run`` for mapInArrow, with memory given back at its end."""

    @functools.wraps(run)
    def wrapped(batches):
        try:
            yield from run(batches)
        finally:
            release()

    return wrapped

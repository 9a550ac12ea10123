"""What the text operators share: words, and texts as byte strings.

A word is a maximal run of characters other than space and 0x09 to 0x0D; for
UTF-8 bytes that is what ``bytes.split`` without arguments returns.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column
from pyspark.sql import functions as F

SEPARATORS = r"[\x20\x09-\x0D]+"


def words_column(text: Column) -> Column:
    """Array of the words of a text; empty for null and blank texts."""
    parts = F.split(F.coalesce(text, F.lit("")), SEPARATORS)
    return F.filter(parts, lambda w: w != "")


def let(value: Column, body) -> Column:
    """``body(value)`` with the value computed once: higher-order functions would evaluate a captured expression for each element."""
    return F.element_at(F.transform(F.array(value), body), 1)


def raw_texts(column: pa.Array) -> list[bytes]:
    """UTF-8 bytes of each text; a null text is empty."""
    return [b"" if x is None else x for x in column.cast(pa.binary()).to_pylist()]


def trim() -> None:
    """Give memory that earlier slices have freed back to the system: an executor's other processes need it."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def slices(batches: Iterator[pa.RecordBatch], rows: int = 512) -> Iterator[pa.RecordBatch]:
    """Arrow batches cut to a few hundred documents, which bounds what a worker holds at once."""
    for batch in batches:
        for start in range(0, batch.num_rows, rows):
            yield batch.slice(start, rows)
        trim()


def byte_slices(batches: Iterator[pa.RecordBatch], column: int, limit: int = 24 << 20) -> Iterator[pa.RecordBatch]:
    """Arrow batches cut so that each slice has about ``limit`` bytes of text, one row at least."""
    for batch in batches:
        ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False), dtype=np.int64)
        start = 0
        while start < batch.num_rows:
            done = int(ends[start - 1]) if start else 0
            stop = max(start + 1, int(np.searchsorted(ends, done + limit, side="right")))
            yield batch.slice(start, stop - start)
            start = stop
            trim()

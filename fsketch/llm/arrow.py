"""Helpers for operators that work on Arrow batches in Python workers."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute  # noqa: F401

#: Bytes of text that are worked on at a time; a single longer text is a slice of its own.
SLICE_BYTES = 1 << 21


def text_bytes(column: pa.Array) -> pa.Array:
    """A string column as binary, without decoding it."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return column.cast(pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary())


def slices(batch: pa.RecordBatch, column: str, most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Parts of a batch that hold about ``most`` bytes of the column each."""
    lengths = text_bytes(batch.column(column))
    sizes = pa.compute.fill_null(pa.compute.binary_length(lengths), 0).to_pylist()
    begin, total = 0, 0
    for i, n in enumerate(sizes):
        if total and total + n > most:
            yield batch.slice(begin, i - begin)
            begin, total = i, 0
        total += n
    if begin < len(sizes):
        yield batch.slice(begin)

"""Arrow helpers shared by the text operators."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc


def slices(
    batches: Iterable[pa.RecordBatch], column: str, max_rows: int = 1024, max_bytes: int = 8 << 20
) -> Iterator[pa.RecordBatch]:
    """Cut batches so that no slice holds more than ``max_bytes`` of ``column``.

    A single longer value forms a slice of its own; empty batches yield nothing.
    """
    for batch in batches:
        n = batch.num_rows
        if not n:
            continue
        lengths = pc.fill_null(pc.binary_length(batch.column(column)), 0)
        ends = np.cumsum(lengths.to_numpy(zero_copy_only=False).astype(np.int64))
        start = 0
        while start < n:
            base = ends[start - 1] if start else 0
            stop = int(np.searchsorted(ends, base + max_bytes, side="right"))
            stop = min(max(stop, start + 1), start + max_rows, n)
            yield batch.slice(start, stop - start)
            start = stop


def texts(batch: pa.RecordBatch, column: str = "text") -> list[str]:
    """Values of a string column; null becomes the empty text."""
    return [x if x is not None else "" for x in batch.column(column).to_pylist()]


def payloads(batch: pa.RecordBatch, column: str = "text") -> list[bytes]:
    """UTF-8 bytes of a string or binary column; null becomes empty."""
    values = batch.column(column)
    if not pa.types.is_binary(values.type):
        values = values.cast(pa.binary())
    return [x if x is not None else b"" for x in values.to_pylist()]


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective scrambler of unsigned 64-bit integers (multiply and xor-shift)."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(31)
    x *= np.uint64(0x7FB5D329728EA185)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x81DADEF4BC2DD44D)
    x ^= x >> np.uint64(33)
    return x

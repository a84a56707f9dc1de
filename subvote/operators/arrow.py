"""List columns as numpy matrices, without a Python object per row."""

from __future__ import annotations

import numpy as np
import pyarrow as pa


def matrix(column: pa.Array) -> np.ndarray:
    """A list column of equal lengths as a two-dimensional view."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    n = len(column)
    flat = column.flatten()
    values = flat.to_numpy(zero_copy_only=False)
    if n and len(values) % n:
        raise ValueError("vectors of different lengths")
    return values.reshape(n, -1) if n else values.reshape(0, 0)


def lists(values: np.ndarray) -> pa.Array:
    """A matrix as a list column."""
    n, width = values.shape
    offsets = pa.array(np.arange(n + 1, dtype=np.int32) * width)
    return pa.ListArray.from_arrays(offsets, pa.array(np.ascontiguousarray(values).ravel()))


def blobs(rows: np.ndarray) -> list[bytes]:
    return [r.tobytes() for r in rows]


def sign_words(x: np.ndarray) -> np.ndarray:
    """Sign bits of every row packed into int64 words, first dimension lowest."""
    n, dim = x.shape
    bits = np.zeros((n, -(-dim // 64) * 64), np.uint8)
    bits[:, :dim] = x >= 0
    return np.packbits(bits, axis=1, bitorder="little").view("<i8")

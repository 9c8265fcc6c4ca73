"""Arrow batches as arrays and back."""

from __future__ import annotations

import numpy as np
import pyarrow as pa


def matrix_of(column: pa.Array, n: int) -> np.ndarray:
    """Rows of a list column whose lists all have length ``n``."""
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return np.asarray(flat, np.float64).reshape(-1, n)


def bytes_of(rows: np.ndarray) -> pa.Array:
    """A binary column with one byte per entry of each row."""
    rows = np.ascontiguousarray(rows, np.uint8)
    offsets = np.arange(len(rows) + 1, dtype=np.int32) * rows.shape[1]
    return pa.Array.from_buffers(pa.binary(), len(rows), [None, pa.py_buffer(offsets.tobytes()), pa.py_buffer(rows.tobytes())])


def words_from(column: pa.Array | pa.ChunkedArray, w: int) -> np.ndarray:
    """Rows of a binary column whose entries all have ``w`` bytes, without an object for each."""
    if isinstance(column, pa.ChunkedArray):
        return np.concatenate([words_from(c, w) for c in column.chunks]) if column.num_chunks else np.zeros((0, w), np.uint8)
    if not len(column):
        return np.zeros((0, w), np.uint8)
    if pa.types.is_large_binary(column.type):
        column = column.cast(pa.binary())
    offsets = np.frombuffer(column.buffers()[1], np.int32, len(column) + 1, 4 * column.offset)
    return np.frombuffer(column.buffers()[2], np.uint8, int(offsets[-1] - offsets[0]), int(offsets[0])).reshape(-1, w)


def lists_of(x: np.ndarray, kind=pa.float64()) -> pa.Array:
    offsets = pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1])
    return pa.ListArray.from_arrays(offsets, pa.array(np.ascontiguousarray(x).reshape(-1), kind))

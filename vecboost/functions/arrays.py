"""Arrow columns of fixed width to NumPy matrices and back, without a Python object a row."""

from __future__ import annotations

import numpy as np
import pyarrow as pa


def list_matrix(column: pa.Array) -> np.ndarray:
    """Rows of a list<double> column of equal lengths."""
    n = len(column)
    return column.flatten().to_numpy(zero_copy_only=False).reshape(n, -1) if n else np.zeros((0, 0))


def to_lists(m: np.ndarray) -> pa.Array:
    n, c = m.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(0, (n + 1) * c, c, dtype=np.int32) if c else np.zeros(n + 1, np.int32)), pa.array(np.ascontiguousarray(m, np.float64).ravel()))


def byte_matrix(column: pa.Array) -> np.ndarray:
    """Rows of a binary column of equal lengths, as uint8."""
    n = len(column)
    if not n:
        return np.zeros((0, 0), np.uint8)
    column = column.cast(pa.binary())
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int32, n + 1, 4 * column.offset)
    if data is None:
        return np.zeros((n, 0), np.uint8)
    return np.frombuffer(data, np.uint8)[at[0] : at[-1]].reshape(n, -1)


def to_bytes(m: np.ndarray) -> pa.Array:
    n, c = m.shape
    offsets = np.arange(n + 1, dtype=np.int32) * np.int32(c)
    return pa.Array.from_buffers(pa.binary(), n, [None, pa.py_buffer(offsets.tobytes()), pa.py_buffer(np.ascontiguousarray(m, np.uint8).tobytes())])

"""Arrow columns of vectors as matrices, and back."""

from __future__ import annotations

import numpy as np
import pyarrow as pa


def to_matrix(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    """An array column of equal lengths as a matrix, without a Python loop."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    n = len(column)
    flat = np.asarray(column.flatten(), dtype=np.float64)
    return flat.reshape(n, -1) if n else np.zeros((0, 0))


def to_column(x: np.ndarray) -> pa.Array:
    """A matrix as an array column."""
    n, d = x.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(0, (n + 1) * d, d, dtype=np.int32) if d else np.zeros(n + 1, np.int32)), pa.array(np.ascontiguousarray(x, dtype=np.float64).ravel()))


def block_distances(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Squared distances of all rows to all centers by one product, clamped at 0."""
    d2 = (x * x).sum(1)[:, None] - 2.0 * (x @ c.T) + (c * c).sum(1)[None, :]
    return np.maximum(d2, 0.0)

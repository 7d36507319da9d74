"""Between Arrow lists and numpy matrices."""

from __future__ import annotations

import numpy as np
import pyarrow as pa


def matrix(col: pa.Array | pa.ChunkedArray, dtype=np.float64) -> np.ndarray:
    """Rows of a list column as a matrix; all lists have one length."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    if not len(col):
        return np.zeros((0, 0), dtype)
    flat = col.flatten().to_numpy(zero_copy_only=False)
    if len(flat) % len(col):
        raise ValueError("vectors differ in dimension")
    return np.asarray(flat, dtype).reshape(len(col), -1)


def lists(values: pa.Array, sizes: np.ndarray) -> pa.ListArray:
    offsets = np.zeros(len(sizes) + 1, np.int32)
    np.cumsum(sizes, out=offsets[1:])
    return pa.ListArray.from_arrays(pa.array(offsets), values)


def sq_distances(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Squared distances by one matrix product; exact for integers up to 2^26."""
    d = np.einsum("ij,ij->i", x, x)[:, None] - 2.0 * (x @ y.T) + np.einsum("ij,ij->i", y, y)[None, :]
    return np.maximum(d, 0.0)

"""Array columns between Arrow and numpy."""

from __future__ import annotations

import numpy as np
import pyarrow as pa


def matrix(column, kind=np.float64) -> np.ndarray:
    """A list column of one width as a matrix."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if not len(column):
        return np.empty((0, 0), dtype=kind)
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(kind, copy=False)
    return flat.reshape(len(column), -1)


def lists(values: np.ndarray, kind) -> pa.ListArray:
    """A matrix as a list column."""
    n, w = values.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(0, n * w + 1, max(w, 1), dtype=np.int32)[: n + 1]), pa.array(np.ascontiguousarray(values).ravel(), type=kind))


def vector(column) -> np.ndarray:
    return column.to_numpy(zero_copy_only=False)

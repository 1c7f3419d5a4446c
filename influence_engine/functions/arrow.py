"""Matrices from and to Arrow list columns, without Python objects between."""

from __future__ import annotations

import numpy as np
import pyarrow as pa


def to_matrix(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    """Rows of equal length as doubles; a column without rows gives an empty matrix."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if not len(column):
        return np.empty((0, 0))
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64, copy=False).reshape(len(column), -1)


def from_matrix(rows: np.ndarray, kind: pa.DataType | None = None) -> pa.Array:
    flat = pa.array(np.ascontiguousarray(rows).ravel(), kind or pa.float64())
    return pa.ListArray.from_arrays(pa.array(np.arange(len(rows) + 1, dtype=np.int32) * rows.shape[1]), flat)

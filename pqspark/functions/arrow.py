"""Vectors between Arrow and numpy."""

from __future__ import annotations

import numpy as np
import pyarrow as pa


def matrix(column: pa.Array, dim: int) -> tuple[np.ndarray, np.ndarray]:
    """(rows that are whole, their [rows, dim] matrix): not null, dim long, all components finite.

    A column without flaws is a view of Arrow's buffer; sliced batches are respected.
    """
    flat = column.flatten()
    if column.null_count == 0 and flat.null_count == 0 and len(flat) == len(column) * dim and (column.value_lengths().to_numpy() == dim).all():
        x = flat.to_numpy(zero_copy_only=False).reshape(-1, dim)
        good = np.isfinite(x).all(axis=1)
        return (np.arange(len(x)), x) if good.all() else (np.flatnonzero(good), x[good])
    rows = [k for k, v in enumerate(column.to_pylist()) if v is not None and len(v) == dim and all(c is not None and np.isfinite(c) for c in v)]
    return np.array(rows, np.int64), np.array([column[k].as_py() for k in rows], np.float64).reshape(len(rows), dim)


def vectors(x: np.ndarray, kind: pa.DataType) -> pa.Array:
    """A matrix as a list column."""
    return pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, x.shape[1] or 1), pa.int32()), pa.array(x.reshape(-1), kind))

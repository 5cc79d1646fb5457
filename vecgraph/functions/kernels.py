"""Numpy kernels that run inside Arrow batches."""

from __future__ import annotations

import numpy as np
import pyarrow as pa


def matrix(col: pa.Array) -> np.ndarray:
    """A list column of equal lengths as a float64 matrix."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    n = len(col)
    flat = col.flatten().to_numpy(zero_copy_only=False).astype(np.float64, copy=False)
    return flat.reshape(n, -1) if n else np.empty((0, 0))


def whole(col: pa.Array) -> np.ndarray:
    """A list column of equally many whole numbers as an int64 matrix (a float would round ids)."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    n = len(col)
    return col.flatten().to_numpy(zero_copy_only=False).astype(np.int64).reshape(n, -1) if n else np.empty((0, 0), np.int64)


def lists(x: np.ndarray, kind: pa.DataType | None = None) -> pa.Array:
    """A matrix as a list column."""
    n, d = x.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * d), pa.array(np.ascontiguousarray(x).ravel(), kind))


def d2_pairs(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Squared distances of all rows of a to all rows of b, components added in order."""
    out = np.zeros((len(a), len(b)))
    for i in range(a.shape[1]):
        diff = a[:, i, None] - b[None, :, i]
        out += diff * diff
    return out


def d2_blas(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The same through one matrix product: fast, rounded differently; for choosing, not for reporting."""
    return np.maximum((a * a).sum(1)[:, None] - 2 * (a @ b.T) + (b * b).sum(1)[None], 0)


def fold(terms: np.ndarray) -> np.ndarray:
    """Sum over the last axis in order (numpy's own sum adds in pairs)."""
    out = np.zeros(terms.shape[:-1])
    for i in range(terms.shape[-1]):
        out += terms[..., i]
    return out


def smallest(d: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Per row of d: places and values of the k smallest, ties by id."""
    k = min(k, d.shape[1])
    order = np.lexsort((np.broadcast_to(ids, d.shape), d))[:, :k]
    return order, np.take_along_axis(d, order, 1)

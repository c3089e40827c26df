"""Vectors as arrays in columns, and blocks of them in tasks."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F

METRICS = ("cosine", "dot", "euclidean")


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def cosine(a: Column, b: Column) -> Column:
    norm = F.sqrt(dot(a, a)) * F.sqrt(dot(b, b))
    return F.when(norm > 0, dot(a, b) / norm).otherwise(0.0)


def similarity(a: Column, b: Column, metric: str) -> Column:
    """Larger is nearer; euclidean distances are negated."""
    if metric == "cosine":
        return cosine(a, b)
    if metric == "dot":
        return dot(a, b)
    if metric == "euclidean":
        square = F.aggregate(F.zip_with(a, b, lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))), F.lit(0.0), lambda s, x: s + x)
        return -F.sqrt(square)
    raise ValueError(f"metric is one of {METRICS}")


def matrix(column: pd.Series, dim: int | None = None) -> np.ndarray:
    """A block of vectors in double precision."""
    if not len(column):
        return np.zeros((0, dim or 0))
    return np.stack(column.to_numpy()).astype(np.float64)


def arrow_matrix(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    """A block of vectors of one length, as Arrow lists, in double precision."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    n = len(column)
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(n, len(flat) // n if n else 0).astype(np.float64)


def vectors_of(x: np.ndarray) -> pa.Array:
    """Rows as Arrow lists in single precision, without nulls."""
    flat = np.ascontiguousarray(x, dtype=np.float32).ravel()
    offsets = np.arange(len(x) + 1, dtype=np.int32) * (x.shape[1] if len(x) else 0)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat), type=pa.list_(pa.field("element", pa.float32(), nullable=False)))


def unit(x: np.ndarray) -> np.ndarray:
    n = np.linalg.norm(x, axis=1, keepdims=True)
    return x / np.where(n > 0, n, 1)


def block_similarity(q: np.ndarray, r: np.ndarray, metric: str) -> np.ndarray:
    """Similarities of all rows of q and r, rounded to nine decimals so that ties do not hang on the order of sums."""
    if metric == "cosine":
        s = unit(q) @ unit(r).T
    elif metric == "dot":
        s = q @ r.T
    elif metric == "euclidean":
        s = -np.sqrt(np.maximum((q * q).sum(1)[:, None] + (r * r).sum(1)[None] - 2 * q @ r.T, 0))
    else:
        raise ValueError(f"metric is one of {METRICS}")
    return np.round(s, 9)


def block_top(qid: np.ndarray, rid: np.ndarray, s: np.ndarray, k: int, exclude_self: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(qid, rid, rank, sim) of the k largest of each row of s, ties by rid."""
    if exclude_self:
        s = np.where(qid[:, None] == rid[None], -np.inf, s)
    if not s.size:
        return tuple(np.empty(0, t) for t in (np.int64, np.int64, np.int32, float))
    k = min(k, s.shape[1])
    least = np.partition(s, s.shape[1] - k, axis=1)[:, s.shape[1] - k]
    row, col = np.nonzero((s >= least[:, None]) & np.isfinite(s))
    order = np.lexsort((rid[col], -s[row, col], row))
    row, col = row[order], col[order]
    first = np.searchsorted(row, np.arange(len(qid)))
    rank = np.arange(len(row)) - first[row] + 1
    keep = rank <= k
    row, col, rank = row[keep], col[keep], rank[keep]
    return qid[row], rid[col], rank.astype(np.int32), s[row, col]

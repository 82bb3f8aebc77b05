"""Similarity of vectors and of token matrices, as expressions and in numpy."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, v: s + v)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    """Cosine of two vectors; 0 where one is zero."""
    size = norm(a) * norm(b)
    return F.when(size == 0, F.lit(0.0)).otherwise(dot(a, b) / size)


def euclidean(a: Column, b: Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: F.pow(x.cast("double") - y.cast("double"), F.lit(2.0))), F.lit(0.0), lambda s, v: s + v))


def unit(rows: np.ndarray) -> np.ndarray:
    """Rows scaled to length 1; zero rows stay zero."""
    size = np.linalg.norm(rows, axis=-1, keepdims=True)
    return np.divide(rows, size, out=np.zeros_like(rows), where=size > 0)


def maxsim(query: np.ndarray, document: np.ndarray) -> float:
    """Late interaction: for each query token the best cosine with a document token, summed."""
    if not len(query) or not len(document):
        return 0.0
    return float((unit(query) @ unit(document).T).max(axis=1).sum())


def matrix(column, width: int | None = None) -> np.ndarray:
    """An Arrow list<float> column as a matrix; null lists become zero rows."""
    lists = column.combine_chunks() if hasattr(column, "combine_chunks") else column
    if lists.null_count or width is None:
        return np.array([v if v is not None else [0.0] * (width or 0) for v in lists.to_pylist()], np.float64).reshape(len(lists), -1)
    return lists.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(lists), width)

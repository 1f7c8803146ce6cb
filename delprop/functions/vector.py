"""Vectors as array<double> columns, and packed symmetric matrices."""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def axpy(scale: Column | float, x: Column, y: Column) -> Column:
    scale = F.lit(scale) if isinstance(scale, (int, float)) else scale
    return F.zip_with(x, y, lambda a, b: scale * a + b)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def outer_packed(a: Column) -> Column:
    """Upper triangle of the outer product with itself, row by row."""
    rows = F.transform(a, lambda x, i: F.transform(F.slice(a, i + 1, F.size(a)), lambda y: x * y))
    return F.flatten(rows)


def array_of(values: np.ndarray) -> Column:
    return F.array(*[F.lit(float(v)) for v in values])


def packed_size(m: int) -> int:
    return m * (m + 1) // 2


@lru_cache(maxsize=4)
def _upper(m: int) -> np.ndarray:
    """The upper triangle's places in a matrix that is read row by row."""
    return np.flatnonzero(np.triu(np.ones((m, m), bool)))


def pack(matrix: np.ndarray) -> np.ndarray:
    return matrix.ravel()[_upper(len(matrix))]


def unpack(values: np.ndarray, m: int) -> np.ndarray:
    out = np.zeros(m * m)
    out[_upper(m)] = values
    out = out.reshape(m, m)
    return out + np.triu(out, 1).T


def matrix_of(column: pa.Array, m: int) -> np.ndarray:
    """Rows of a list<double> Arrow column."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return column.flatten().to_numpy(zero_copy_only=False).astype(float, copy=False).reshape(len(column), m)

"""Piecewise linear interpolants: one-dimensional for the logistic gradient, several-dimensional for softmax.

The binary rule's factor is f(z) = 1 / (1 + e^z).  On each of ``cells`` equal
cells of [-bound, bound) it is replaced by the chord; outside by the constant
at the nearer end.  Cells are found by arithmetic, so no table is joined.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

BOUND = 20.0
CELLS = 10**6


def falling(z: np.ndarray | float) -> np.ndarray:
    """1 / (1 + e^z) without overflow."""
    z = np.asarray(z, float)
    e = np.exp(-np.abs(z))
    return np.where(z >= 0, e / (1 + e), 1 / (1 + e))


def pieces(z: np.ndarray, bound: float = BOUND, cells: int = CELLS) -> tuple[np.ndarray, np.ndarray]:
    """Slope and offset at each margin."""
    z = np.asarray(z, float)
    h = 2 * bound / cells
    inside = np.abs(z) < bound
    low = -bound + np.floor((np.where(inside, z, 0) + bound) / h) * h
    slope = (falling(low + h) - falling(low)) / h
    offset = falling(low) - slope * low
    return np.where(inside, slope, 0.0), np.where(inside, offset, falling(np.clip(z, -bound, bound)))


def coefficients(z: Column, bound: float = BOUND, cells: int = CELLS) -> tuple[Column, Column]:
    """Slope and offset as Column arithmetic, inside generated code.

    The margin enters the arithmetic many times, so it should be a stored
    column; for a costly expression take :func:`coefficients_of`.
    """
    h = 2 * bound / cells

    def f(x: Column) -> Column:
        return 1.0 / (1.0 + F.exp(x))

    inside = F.abs(z) < bound
    low = F.floor((z + bound) / h) * h - bound
    slope = (f(low + h) - f(low)) / h
    end = F.greatest(F.least(z, F.lit(bound)), F.lit(-bound))
    return F.when(inside, slope).otherwise(0.0), F.when(inside, f(low) - slope * low).otherwise(f(end))


def coefficients_of(z: Column, bound: float = BOUND, cells: int = CELLS) -> Column:
    """struct<a, b> by an Arrow function, which computes its argument once a row."""

    @F.pandas_udf("a double, b double")
    def both(margin: pd.Series) -> pd.DataFrame:
        a, b = pieces(margin.to_numpy(float), bound, cells)
        return pd.DataFrame({"a": a, "b": b})

    return both(z)


def table(spark: SparkSession, f: Callable[[Column], Column], low: float, high: float, cells: int) -> DataFrame:
    """(cell, low, high, slope, offset) of the interpolant of any Column function over equal cells."""
    h = (high - low) / cells
    rows = spark.range(cells).select(F.col("id").alias("cell"), (F.lit(low) + F.col("id") * h).alias("low"), (F.lit(low) + (F.col("id") + 1) * h).alias("high"))
    slope = (f(F.col("high")) - f(F.col("low"))) / h
    return rows.withColumn("slope", slope).withColumn("offset", f(F.col("low")) - F.col("slope") * F.col("low"))


def softmax(u: np.ndarray) -> np.ndarray:
    e = np.exp(u - u.max(-1, keepdims=True))
    return e / e.sum(-1, keepdims=True)


def softmax_tangent(u: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Jacobians A (rows, q, q) and offsets c with softmax ~ A u + c at each row of logits: the limit of small cells."""
    p = softmax(u)
    jacobian = p[:, :, None] * np.eye(u.shape[1]) - p[:, :, None] * p[:, None, :]
    return jacobian, p - np.einsum("nij,nj->ni", jacobian, u)


def softmax_simplex(u: np.ndarray, dx: float) -> tuple[np.ndarray, np.ndarray]:
    """The affine piece of a grid interpolant over logit differences to the last class.

    Each grid cube splits into simplices by the order of the coordinates'
    fractional parts; the piece agrees with softmax at the simplex's vertices.
    """
    n, q = u.shape
    d = u[:, :-1] - u[:, -1:]
    base = np.floor(d / dx)
    order = np.argsort(-(d / dx - base), axis=1, kind="stable")
    corner = base.copy()
    values = [softmax(np.c_[corner * dx, np.zeros(n)])]
    for k in range(q - 1):
        corner[np.arange(n), order[:, k]] += 1
        values.append(softmax(np.c_[corner * dx, np.zeros(n)]))
    slopes = np.zeros((n, q, q))
    for k in range(q - 1):
        slopes[np.arange(n), :, order[:, k]] = (values[k + 1] - values[k]) / dx
    slopes[:, :, -1] = -slopes[:, :, :-1].sum(2)
    offset = values[0] - np.einsum("nij,nj->ni", slopes[:, :, :-1], base * dx)
    return slopes, offset


def softmax_pieces(u: np.ndarray, method: str = "tangent", dx: float = 0.05) -> tuple[np.ndarray, np.ndarray]:
    if method == "tangent":
        return softmax_tangent(u)
    if method == "simplex":
        return softmax_simplex(u, dx)
    raise ValueError("method must be 'tangent' or 'simplex'")


def softmax_column(method: str = "tangent", dx: float = 0.05):
    """Arrow UDF: logits array -> interpolated class probabilities."""

    @F.pandas_udf("array<double>")
    def interpolated(logits: pd.Series) -> pd.Series:
        u = np.array(logits.tolist(), float)
        slopes, offset = softmax_pieces(u, method, dx)
        return pd.Series(list(np.einsum("nij,nj->ni", slopes, u) + offset))

    return interpolated

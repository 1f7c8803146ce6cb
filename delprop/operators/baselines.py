"""Baselines: closed form (direct and by rank updates), influence estimates, library solvers, and no update."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from delprop.functions.vector import array_of, dot, matrix_of, unpack
from delprop.operators.capture import MAX_DENSE, capture_tail
from delprop.operators.gram import arrow_gram, summed, total_gram
from delprop.operators.replay import _local_rows
from delprop.operators.train import batch_gradient
from delprop.spec import ModelSpec


def removed_block(samples: DataFrame, removals: DataFrame, m: int) -> tuple[np.ndarray, np.ndarray]:
    rows = samples.join(removals.select("sample_id").distinct(), "sample_id", "left_semi").withColumn("block_id", F.lit(0))
    return _local_rows(rows, m).get(0, (np.zeros((0, m)), np.zeros(0)))


def global_sums(samples: DataFrame, m: int) -> tuple[np.ndarray, np.ndarray, int]:
    r = total_gram(samples, m).first()
    return unpack(np.array(r.gram), m), np.array(r.cross), r.cnt


def removed_sums(samples: DataFrame, removals: DataFrame, m: int) -> tuple[np.ndarray, np.ndarray, int]:
    """Gram and cross sums and number of the removed rows, in one aggregation whatever their number."""
    r = total_gram(samples.join(removals.select("sample_id").distinct(), "sample_id", "left_semi"), m).first()
    return (np.zeros((m, m)), np.zeros(m), 0) if r is None else (unpack(np.array(r.gram), m), np.array(r.cross), r.cnt)


def normal_eq_sums(sums: tuple[np.ndarray, np.ndarray, int], removed: tuple[np.ndarray, np.ndarray, int], lam: float) -> np.ndarray:
    """Ridge solution of the survivors from cached sums and the removed rows' sums."""
    left = sums[2] - removed[2]
    if left <= 0:
        return np.zeros(len(sums[1]))
    return np.linalg.solve(sums[0] - removed[0] + left * lam / 2 * np.eye(len(sums[1])), sums[1] - removed[1])


def normal_eq(sums: tuple[np.ndarray, np.ndarray, int], removed: tuple[np.ndarray, np.ndarray], lam: float, method: str = "solve") -> np.ndarray:
    """Ridge solution of the survivors from cached sums.

    ``woodbury`` updates in the cached eigenvectors (the ridge term depends on
    the number of survivors, so the inverse itself cannot be cached) and
    solves a system of the rank of the removed rows, which is at most their
    number and at most that of the features.
    """
    gram, cross, n = sums
    x, y = removed
    if n - len(y) <= 0:
        return np.zeros(len(cross))
    if method == "solve":
        return np.linalg.solve(gram - x.T @ x + (n - len(y)) * lam / 2 * np.eye(len(cross)), cross - x.T @ y)
    thin = np.linalg.qr(x, mode="r") if len(x) > x.shape[1] else x  # the same rows' sums
    return _rank_update(gram, thin, cross - x.T @ y, n - len(y), lam)


def _rank_update(gram: np.ndarray, thin: np.ndarray, rhs: np.ndarray, left: int, lam: float) -> np.ndarray:
    """(gram - thin' thin + ridge) w = rhs in the eigenvectors of ``gram``."""
    values, q = np.linalg.eigh(gram)
    inverse = values + left * lam / 2
    z, u = q.T @ rhs / inverse, thin @ q
    if len(u):
        inner = np.eye(len(u)) - (u / inverse) @ u.T
        z = z + (u.T @ np.linalg.solve(inner, u @ z)) / inverse
    return q @ z


def normal_eq_rank(sums: tuple[np.ndarray, np.ndarray, int], removed: tuple[np.ndarray, np.ndarray, int], lam: float) -> np.ndarray:
    """The rank update from the removed rows' sums: their Gram matrix is factored, so no removed row is held in this process."""
    left = sums[2] - removed[2]
    if left <= 0:
        return np.zeros(len(sums[1]))
    values, vectors = np.linalg.eigh(removed[0])
    kept = values > values[-1] * len(values) * np.finfo(float).eps
    return _rank_update(sums[0], np.sqrt(values[kept])[:, None] * vectors[:, kept].T, sums[1] - removed[1], left, lam)


def hessian(samples: DataFrame, w: np.ndarray, spec: ModelSpec) -> np.ndarray:
    """Of the regularised objective over ``samples``: one weighted Gram aggregation."""
    if spec.size > MAX_DENSE:
        raise ValueError(f"an influence estimate needs a dense Hessian of order {spec.size}; the limit is {MAX_DENSE}")
    ridge = spec.lam * np.eye(spec.size)
    if spec.kind == "linear":
        gram, _, n = global_sums(samples, spec.m)
        return 2 / n * gram + ridge
    if spec.kind == "binary":
        z = dot(F.col("features"), array_of(w))
        root = F.exp(-F.abs(z) / 2) / (1.0 + F.exp(-F.abs(z)))
        scaled = samples.select(F.lit(0).alias("block_id"), F.transform("features", lambda v: v * root).alias("features"), "label")
        r = arrow_gram(scaled, spec.m).first()
        return unpack(np.array(r.gram), spec.m) / r.cnt + ridge
    r = capture_tail(samples, w, spec).first()
    return -unpack(np.array(r.gram), spec.size) / r.cnt + ridge


def influence(samples: DataFrame, w: np.ndarray, removals: DataFrame, spec: ModelSpec, of: str = "all", h: np.ndarray | None = None) -> np.ndarray:
    """One Taylor step for leaving rows out: w + H^-1 (sum of their loss gradients) / n.

    ``of='survivors'`` takes the Hessian and the count of the survivors
    instead: a Newton step, stronger than the published estimate.
    """
    ids = removals.select("sample_id").distinct()
    gone, removed = total_gradient(samples.join(ids, "sample_id", "left_semi"), w, spec)
    if not removed:
        return w.copy()
    if of == "survivors":
        rest = samples.join(ids, "sample_id", "left_anti")
        whole, n = total_gradient(samples, w, spec)
        return w - np.linalg.solve(hessian(rest, w, spec), (whole - gone) / (n - removed) + spec.lam * w)
    h = hessian(samples, w, spec) if h is None else h
    return w + np.linalg.solve(h, gone) / samples.count()


def total_gradient(samples: DataFrame, w: np.ndarray, spec: ModelSpec) -> tuple[np.ndarray, int]:
    """Sum of the sample gradients over all rows, without the penalty, and their number."""

    def partial(batch: pa.RecordBatch) -> Iterator[tuple[int, int, np.ndarray]]:
        x, y = matrix_of(batch.column("features"), spec.m), batch.column("label").to_numpy(zero_copy_only=False)
        yield 0, len(y), batch_gradient(x, y, w, spec)

    r = summed(samples.select("features", F.col("label").cast("double").alias("label")), partial, spec.size).first()
    return (np.zeros(spec.size), 0) if r is None else (np.array(r.sums), r.cnt)


def stale(w: np.ndarray) -> np.ndarray:
    """No update at all: the lower reference."""
    return w.copy()


def library_fit(samples: DataFrame, spec: ModelSpec, max_iter: int = 200) -> np.ndarray:
    """The library's solver for the same objective; the intercept stays an ordinary, regularised feature.

    The solvers set the coefficient of a constant column to zero, so linear
    and binary rows also enter mirrored (features and label negated), which
    leaves the objective as it is.  For softmax the constant column's weights
    are therefore not comparable.
    """
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.functions import array_to_vector
    from pyspark.ml.regression import LinearRegression

    rows = samples.select("features", F.col("label").cast("double").alias("label"))
    if spec.kind != "softmax":
        rows = rows.unionByName(rows.select(F.transform("features", lambda v: -v).alias("features"), (-F.col("label")).alias("label")))
    rows = rows.select(array_to_vector("features").alias("features"), "label")
    if spec.kind == "linear":  # half squared loss there, hence lambda / 2
        fit = LinearRegression(regParam=spec.lam / 2, elasticNetParam=0.0, fitIntercept=False, standardization=False, maxIter=max_iter, tol=1e-12, solver="l-bfgs").fit(rows)
        return fit.coefficients.toArray()
    options = dict(regParam=spec.lam, elasticNetParam=0.0, fitIntercept=False, standardization=False, maxIter=max_iter, tol=1e-12)
    if spec.kind == "binary":
        fit = LogisticRegression(family="binomial", **options).fit(rows.withColumn("label", (F.col("label") + 1) / 2))
        return fit.coefficients.toArray()
    return LogisticRegression(family="multinomial", **options).fit(rows).coefficientMatrix.toArray().ravel()

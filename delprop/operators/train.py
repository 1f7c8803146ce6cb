"""Objectives, gradients, training and retraining by gradient descent in all schedules.

Two engines give the same iterates.  ``local`` gathers the touched rows once
and iterates in one process; it is taken while the rows fit ``local_bytes``.
``jobs`` runs one aggregation an iteration and holds only the parameters.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from delprop.functions.linearize import falling, pieces, softmax, softmax_pieces
from delprop.functions.vector import array_of, dot, matrix_of
from delprop.operators.gram import by_block, summed
from delprop.operators.schedule import assign
from delprop.spec import ModelSpec

LOCAL_BYTES = 1 << 30

Blocks = dict[int, tuple[np.ndarray, np.ndarray]]


@dataclass
class Trained:
    w: np.ndarray
    trajectory: np.ndarray  # (tau + 1, size); empty unless kept
    n: int


def objective(samples: DataFrame, w: np.ndarray, spec: ModelSpec) -> DataFrame:
    """One row: the regularised loss of the whole of ``samples``."""
    x, y = F.col("features"), F.col("label")
    penalty = spec.lam / 2 * float(w @ w)
    if spec.kind == "linear":
        each = F.pow(y - dot(x, array_of(w)), F.lit(2.0))
    elif spec.kind == "binary":
        z = y * dot(x, array_of(w))
        each = F.greatest(-z, F.lit(0.0)) + F.log1p(F.exp(-F.abs(z)))
    else:
        logits = F.array(*[dot(x, array_of(row)) for row in w.reshape(spec.q, spec.m)])
        top = F.array_max(logits)
        each = top + F.log(F.aggregate(logits, F.lit(0.0), lambda s, u: s + F.exp(u - top))) - F.element_at(logits, y.cast("int") + 1)
    return samples.agg((F.avg(each) + F.lit(penalty)).alias("objective"))


def sample_factor(spec: ModelSpec, w: np.ndarray) -> Column:
    """The factor (array over classes for softmax) by which a sample's features enter its gradient."""
    x, y = F.col("features"), F.col("label")
    if spec.kind == "linear":
        return 2.0 * (dot(x, array_of(w)) - y)
    if spec.kind == "binary":
        return -y / (1.0 + F.exp(y * dot(x, array_of(w))))
    logits = F.array(*[dot(x, array_of(row)) for row in w.reshape(spec.q, spec.m)])
    powers = F.transform(logits, lambda u: F.exp(u - F.array_max(logits)))
    total = F.aggregate(powers, F.lit(0.0), lambda s, u: s + u)
    return F.transform(powers, lambda u, k: u / total - F.when(k == y.cast("int"), 1.0).otherwise(0.0))


def gradient(samples: DataFrame, w: np.ndarray, spec: ModelSpec, by: str | None = None) -> DataFrame:
    """([by,] pos, gradient): mean sample gradient plus the penalty's, in long form."""
    keys = [by] if by else []
    factor = sample_factor(spec, w)
    x = F.col("features")
    each = F.flatten(F.transform(factor, lambda f: F.transform(x, lambda v: f * v))) if spec.kind == "softmax" else F.transform(x, lambda v: factor * v)
    long = samples.select(*keys, F.posexplode(each).alias("pos", "v")).groupBy(*keys, "pos").agg(F.avg("v").alias("g"))
    return long.select(*keys, "pos", (F.col("g") + spec.lam * F.element_at(array_of(w), F.col("pos") + 1)).alias("gradient"))


def batch_gradient(x: np.ndarray, y: np.ndarray, w: np.ndarray, spec: ModelSpec) -> np.ndarray:
    """Sum (not mean) of the sample gradients, without the penalty."""
    if spec.kind == "linear":
        return 2 * x.T @ (x @ w - y)
    if spec.kind == "binary":
        return -x.T @ (y * falling(y * (x @ w)))
    p = softmax(x @ w.reshape(spec.q, spec.m).T)
    p[np.arange(len(y)), y.astype(int)] -= 1
    return (p.T @ x).ravel()


def linearized_gradient(x: np.ndarray, y: np.ndarray, w: np.ndarray, spec: ModelSpec, at: np.ndarray | None = None, pieces_of: dict | None = None) -> np.ndarray:
    """As :func:`batch_gradient` with the non-linear factor replaced by its piece at parameters ``at``."""
    at, options = w if at is None else at, pieces_of or {}
    if spec.kind == "linear":
        return batch_gradient(x, y, w, spec)
    if spec.kind == "binary":
        a, b = pieces(y * (x @ at), **options)
        return -x.T @ (a * (x @ w) + b * y)
    slopes, offset = softmax_pieces(x @ at.reshape(spec.q, spec.m).T, **options)
    p = np.einsum("nij,nj->ni", slopes, x @ w.reshape(spec.q, spec.m).T) + offset
    p[np.arange(len(y)), y.astype(int)] -= 1
    return (p.T @ x).ravel()


def gather(blocked: DataFrame, m: int, local_bytes: int = LOCAL_BYTES) -> Blocks | None:
    """Rows by block in this process, or None if they would not fit ``local_bytes``."""
    if blocked.count() * (m + 2) * 8 > local_bytes:
        return None
    table = blocked.select("block_id", "sample_id", "features", F.col("label").cast("double").alias("label")).toArrow()
    if not table.num_rows:
        return {}
    table = table.sort_by([("block_id", "ascending"), ("sample_id", "ascending")])
    x, y = matrix_of(table.column("features"), m), table.column("label").to_numpy()
    return {block: (x[own], y[own]) for block, own in by_block(table.column("block_id").to_numpy())}


def descend(blocks: Blocks, spec: ModelSpec, n_blocks: int, keep: bool = False, step=batch_gradient, path: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Run the schedule over local blocks; a block without rows only shrinks the parameters.

    ``path`` is where a kept trajectory goes, such as a mapped file (tau + 1, size).
    """
    w = spec.start()
    if keep and path is None:
        path = np.empty((spec.tau + 1, spec.size))
    for t in range(spec.tau):
        if keep:
            path[t] = w
        eta, rows = spec.rate(t), blocks.get(t % n_blocks)
        shrunk = (1 - eta * spec.lam) * w
        w = shrunk if rows is None or not len(rows[1]) else shrunk - eta / len(rows[1]) * step(rows[0], rows[1], w, spec)
    if keep:
        path[spec.tau] = w
    return w, path if keep else np.zeros((0, spec.size))


def _descend_jobs(blocked: DataFrame, spec: ModelSpec, n_blocks: int, keep: bool, step) -> tuple[np.ndarray, np.ndarray]:
    w, path = spec.start(), []
    rows = blocked.select(F.col("block_id").cast("int").alias("block_id"), "features", F.col("label").cast("double").alias("label")).persist()
    for t in range(spec.tau):
        if keep:
            path.append(w)

        def partial(batch: pa.RecordBatch, w: np.ndarray = w) -> Iterator[tuple[int, int, np.ndarray]]:
            x, y = matrix_of(batch.column("features"), spec.m), batch.column("label").to_numpy(zero_copy_only=False)
            yield 0, len(y), step(x, y, w, spec)

        eta = spec.rate(t)
        got = summed(rows.where(F.col("block_id") == t % n_blocks), partial, spec.size).first()
        w = (1 - eta * spec.lam) * w
        if got is not None and got.cnt:
            w = w - eta / got.cnt * np.array(got.sums)
    rows.unpersist()
    return w, np.array([*path, w]) if keep else np.zeros((0, spec.size))


def train(samples: DataFrame, spec: ModelSpec, n: int | None = None, keep_trajectory: bool = False, engine: str = "auto", linearized: dict | None = None, local_bytes: int = LOCAL_BYTES) -> Trained:
    """Gradient descent over ``samples``; ``n`` is the size of the undeleted set (that of ``samples`` if not given).

    ``linearized`` (options of the interpolant, may be empty) trains with the
    piecewise linear rule instead of the exact one.
    """
    n = samples.count() if n is None else n
    return train_blocks(assign(samples, spec, n), spec, n, keep_trajectory, engine, linearized, local_bytes)


def train_blocks(blocked: DataFrame, spec: ModelSpec, n: int, keep_trajectory: bool = False, engine: str = "auto", linearized: dict | None = None, local_bytes: int = LOCAL_BYTES) -> Trained:
    """As :func:`train`, on rows that have their blocks."""
    n_blocks = spec.blocks(n)

    def interpolated(x: np.ndarray, y: np.ndarray, w: np.ndarray, own: ModelSpec) -> np.ndarray:
        return linearized_gradient(x, y, w, own, pieces_of=linearized)

    step = batch_gradient if linearized is None else interpolated
    blocks = gather(blocked, spec.m, local_bytes) if engine in ("auto", "local") else None
    if blocks is not None:
        w, path = descend(blocks, spec, n_blocks, keep_trajectory, step)
    elif engine == "local":
        raise MemoryError("the touched rows do not fit local_bytes; use engine='jobs'")
    else:
        w, path = _descend_jobs(blocked, spec, n_blocks, keep_trajectory, step)
    return Trained(w, path, n)


def survivors(samples: DataFrame, removals: DataFrame) -> DataFrame:
    return samples.join(removals.select("sample_id").distinct(), "sample_id", "left_anti")


def retrain(samples: DataFrame, removals: DataFrame, spec: ModelSpec, n: int | None = None, **options) -> Trained:
    """The exact baseline: the same schedule with the removed rows left out of every batch."""
    n = samples.count() if n is None else n
    if spec.schedule == "single":  # the touched rows are chosen before the deletion
        return train_blocks(survivors(assign(samples, spec, n), removals), spec, n, **options)
    return train(survivors(samples, removals), spec, n, **options)


def long_form(w: np.ndarray, spark, **labels) -> DataFrame:
    """(labels, pos, value): a parameter vector as rows."""
    rows = [(*labels.values(), i, float(v)) for i, v in enumerate(w)]
    kinds = "".join(f"{k} {'int' if isinstance(v, int) else 'string'}, " for k, v in labels.items())
    return spark.createDataFrame(rows, f"{kinds}pos int, value double")

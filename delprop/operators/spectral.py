"""Spectral update: the iterations as powers of eigenvalues that shift by the removed rows' share.

The generic rule w <- s w + (eta / n') (C' w + D') with constant C' is diagonal
in the eigenvectors of the undeleted C; its eigenvalues move, to first order,
by the quadratic forms of the removed part.  Online work is one Spark job that
returns two vectors and a count a removal set, whatever the size of the data.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Row
from pyspark.sql import functions as F

from delprop.functions.linearize import pieces, softmax_pieces
from delprop.functions.vector import matrix_of, unpack
from delprop.operators.capture import Capture, capture_tail, piece_sums
from delprop.operators.gram import by_block, summed, total_gram
from delprop.operators.replay import load_sums, removed_rows, removed_share_of, run
from delprop.operators.train import Blocks
from delprop.spec import ModelSpec


@dataclass
class Eigen:
    """Eigenvectors and eigenvalues of the undeleted C, its D, and the number of rows."""

    q: np.ndarray
    c: np.ndarray
    d: np.ndarray
    n: int


def fit_eigen(samples: DataFrame, spec: ModelSpec) -> Eigen:
    """Linear models: C = -2 X'X and D = 2 X'y, in one aggregation; the decomposition is of order m."""
    r = total_gram(samples, spec.m).first()
    return eigen_of(unpack(np.array(r.gram), spec.m), np.array(r.cross), r.cnt)


def eigen_of(gram: np.ndarray, cross: np.ndarray, n: int) -> Eigen:
    c, q = np.linalg.eigh(-2 * gram)
    return Eigen(q, c, 2 * cross, n)


def closed_form(c: np.ndarray, g: np.ndarray, z: np.ndarray, n: int, spec: ModelSpec, first: int, last: int, closed: bool = True) -> np.ndarray:
    """Eigen-coordinates after iterations first..last-1.

    With a constant rate the sum is geometric, O(m); otherwise (or with
    ``closed=False``) suffix products are accumulated.
    """
    if np.isscalar(spec.eta) and closed:
        eta, steps = float(spec.eta), last - first
        rho = 1 - eta * spec.lam + eta * c / n
        power = rho**steps
        near = np.abs(1 - rho) < 1e-12
        series = np.where(near, steps, (1 - power) / np.where(near, 1, 1 - rho))
        return power * z + eta / n * g * series
    for t in range(first, last):
        eta = spec.rate(t)
        z = (1 - eta * spec.lam + eta * c / n) * z + eta / n * g
    return z


def _finish(eigen: Eigen, shift: np.ndarray, d: np.ndarray, n: int, w: np.ndarray, spec: ModelSpec, first: int, closed: bool, exact: np.ndarray | None = None) -> np.ndarray:
    if n <= 0:
        for t in range(first, spec.tau):
            w = (1 - spec.rate(t) * spec.lam) * w
        return w
    q, c = eigen.q, eigen.c - shift
    if exact is not None:
        c, q = np.linalg.eigh((eigen.q * eigen.c) @ eigen.q.T - exact)
    return q @ closed_form(c, q.T @ d, q.T @ w, n, spec, first, spec.tau, closed)


def removed_projection(samples: DataFrame, removals: DataFrame, q: np.ndarray) -> DataFrame:
    """(block_id, cnt, sums): for each removal set (``block_id`` of ``removals``; 0 without one) the number of its rows, the sums of their squares along each eigenvector, and X'y.

    Partial sums are products of Arrow batches with the eigenvectors, for any
    number of features; the sums of each task then meet in a keyed sum.
    """
    m = len(q)
    sets = removals if "block_id" in removals.columns else removals.withColumn("block_id", F.lit(0))
    rows = samples.select("sample_id", "features", F.col("label").cast("double").alias("label")).join(sets.select("block_id", "sample_id").distinct(), "sample_id")

    def partial(batch: pa.RecordBatch) -> Iterator[tuple[int, int, np.ndarray]]:
        x, y = matrix_of(batch.column("features"), m), batch.column("label").to_numpy(zero_copy_only=False)
        squares = (x @ q) ** 2
        for block, own in by_block(batch.column("block_id").to_numpy(zero_copy_only=False)):
            yield block, len(own), np.r_[squares[own].sum(0), x[own].T @ y[own]]

    return summed(rows.select("block_id", "features", "label"), partial, 2 * m)


def spectral_linear(eigen: Eigen, samples: DataFrame, removals: DataFrame, spec: ModelSpec, closed: bool = True, eigen_update: str = "first_order") -> np.ndarray:
    if eigen_update == "exact":
        r = total_gram(samples.join(removals.select("sample_id").distinct(), "sample_id", "left_semi"), spec.m).first()
        gone, g, cross = (0, np.zeros((spec.m, spec.m)), np.zeros(spec.m)) if r is None else (r.cnt, unpack(np.array(r.gram), spec.m), np.array(r.cross))
        return _finish(eigen, np.zeros(spec.m), eigen.d - 2 * cross, eigen.n - gone, spec.start(), spec, 0, closed, -2 * g)
    return _shifted(eigen, removed_projection(samples, removals, eigen.q).first(), spec, closed)


def _shifted(eigen: Eigen, r: Row | None, spec: ModelSpec, closed: bool = True) -> np.ndarray:
    sums, gone = (np.zeros(2 * spec.m), 0) if r is None else (np.array(r.sums), r.cnt)
    return _finish(eigen, -2 * sums[: spec.m], eigen.d - 2 * sums[spec.m :], eigen.n - gone, spec.start(), spec, 0, closed)


def spectral_many(eigen: Eigen, samples: DataFrame, removals: DataFrame, spec: ModelSpec) -> dict[object, np.ndarray]:
    """All removal sets of ``removals`` (subset_id, sample_id) from one job; a set none of whose ids exist gets the model without a removal."""
    names = sorted(r[0] for r in removals.select("subset_id").distinct().collect())  # one model each
    numbers = samples.sparkSession.createDataFrame([(s, i) for i, s in enumerate(names)], f"subset_id {dict(removals.dtypes)['subset_id']}, block_id int")
    found = {r.block_id: r for r in removed_projection(samples, removals.join(F.broadcast(numbers), "subset_id"), eigen.q).collect()}
    return {s: _shifted(eigen, found.get(i), spec) for i, s in enumerate(names)}


def gd_from_gram(gram: np.ndarray, cross: np.ndarray, n: int, spec: ModelSpec) -> np.ndarray:
    """Full-batch surrogate of a mini-batch run, from the global sums alone."""
    w = spec.start()
    for t in range(spec.tau):
        eta = spec.rate(t)
        w = (1 - eta * spec.lam) * w - 2 * eta / n * (gram @ w - cross)
    return w


def switch_point(spec: ModelSpec, ts: float | None = 0.7, ts_delta: float | None = None, gradients: list[float] | None = None) -> int:
    """Iteration from which the pieces are frozen: a fraction of all, or the first with a gradient norm below ``ts_delta``."""
    if ts_delta is not None:
        return next((t for t, g in enumerate(gradients or []) if g < ts_delta), spec.tau)
    return int(ts * spec.tau)


@dataclass
class LogisticSpectral:
    """Capture up to the switch point and the frozen tail in eigen-coordinates."""

    capture: Capture
    eigen: Eigen
    at: int


def fit_logistic(samples: DataFrame, capture: Capture, at: int) -> LogisticSpectral:
    """One full-data job at the switch point's parameters; the capture is cut there."""
    return frozen_tail(capture, at, capture_tail(samples, capture.trajectory[at], capture.spec, **capture.options).first())


def frozen_tail(capture: Capture, at: int, r: Row) -> LogisticSpectral:
    """As :func:`fit_logistic`, from the row of sums (cnt, gram, cross) at the switch point's parameters."""
    spec = capture.spec
    c, q = np.linalg.eigh(unpack(np.array(r.gram), spec.size))
    head = Capture(spec, capture.n, capture.blocks, capture.factors, capture.trajectory, capture.options, at)
    return LogisticSpectral(head, Eigen(q, c, np.array(r.cross), r.cnt), at)


def frozen_share(x: np.ndarray, y: np.ndarray, q: np.ndarray, w: np.ndarray, spec: ModelSpec, options: dict) -> tuple[np.ndarray, np.ndarray]:
    """Removed rows' quadratic forms along the eigenvectors, and their part of D, with pieces at ``w``."""
    if spec.kind == "binary":
        a, b = pieces(y * (x @ w), **options)
        return (a[:, None] * (x @ q) ** 2).sum(0), x.T @ (b * y)
    slopes, offset = softmax_pieces(x @ w.reshape(spec.q, spec.m).T, **options)
    along = np.einsum("nk,ikc->nic", x, q.reshape(spec.q, spec.m, -1))
    rest = -offset
    rest[np.arange(len(y)), y.astype(int)] += 1
    return -np.einsum("nic,nij,njc->c", along, slopes, along), (rest.T @ x).ravel()


def spectral_logistic(model: LogisticSpectral, samples: DataFrame, removals: DataFrame, closed: bool = True) -> np.ndarray:
    """Replay to the switch point, then the closed form with shifted eigenvalues; binary or softmax."""
    capture, spec, q = model.capture, model.capture.spec, model.eigen.q
    w = run(capture, load_sums(capture), removed_share_of(capture, removed_rows(samples, removals, spec, capture.n)), model.at)
    frozen, options = capture.trajectory[model.at], capture.options

    def partial(batch: pa.RecordBatch) -> Iterator[tuple[int, int, np.ndarray]]:
        x, y = matrix_of(batch.column("features"), spec.m), batch.column("label").to_numpy(zero_copy_only=False)
        yield 0, len(y), np.concatenate(frozen_share(x, y, q, frozen, spec, options))

    rows = samples.join(removals.select("sample_id").distinct(), "sample_id", "left_semi")
    r = summed(rows.select("features", F.col("label").cast("double").alias("label")), partial, 2 * spec.size).first()
    return _finish_logistic(model, w, np.zeros(2 * spec.size) if r is None else np.array(r.sums), 0 if r is None else r.cnt)


def _finish_logistic(model: LogisticSpectral, w: np.ndarray, sums: np.ndarray, gone: int) -> np.ndarray:
    spec, eigen = model.capture.spec, model.eigen
    return _finish(eigen, sums[: spec.size], eigen.d - sums[spec.size :], eigen.n - gone, w, spec, model.at, True)


def frozen_sums(parts: Callable[[], Iterable[tuple[np.ndarray, np.ndarray]]], n: int, model: LogisticSpectral) -> np.ndarray:
    """:func:`frozen_share` of ``n`` rows that come in parts, as one vector: row by row, or, for more rows than parameters, from their summed C."""
    capture, spec, q = model.capture, model.capture.spec, model.eigen.q
    frozen, options = capture.trajectory[model.at], capture.options
    if n <= spec.size:
        return sum((np.concatenate(frozen_share(x, y, q, frozen, spec, options)) for x, y in parts()), np.zeros(2 * spec.size))
    c, d = np.zeros((spec.size, spec.size)), np.zeros(spec.size)
    for x, y in parts():
        a, b = piece_sums(x, y, frozen, spec, options)
        c += a
        d += b
    return np.concatenate([((c @ q) * q).sum(0), d])


def finish_logistic(model: LogisticSpectral, w: np.ndarray, rows: Blocks) -> np.ndarray:
    """The tail from parameters ``w`` with the removed rows (block 0) in this process."""
    capture, spec = model.capture, model.capture.spec
    x, y = rows.get(0, (np.zeros((0, spec.m)), np.zeros(0)))
    sums = np.concatenate(frozen_share(x, y, model.eigen.q, capture.trajectory[model.at], spec, capture.options)) if len(y) else np.zeros(2 * spec.size)
    return _finish_logistic(model, w, sums, len(y))

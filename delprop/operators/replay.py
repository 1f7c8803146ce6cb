"""Replay: rerun the iterations on captured sums minus the removed rows' share.

The removed part is never formed as a matrix: its action on the parameters is
two thin products; beyond a bound it is aggregated like the captured sums.  The
recurrence runs in one process over an ordered stream of blocks; many removal
sets run side by side, one task a set.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from typing import Any

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Row
from pyspark.sql import functions as F

from delprop.functions.linearize import pieces, softmax_pieces
from delprop.functions.vector import matrix_of, packed_size, unpack
from delprop.operators.capture import Capture, iteration_sums, steps_of
from delprop.operators.gram import block_gram, by_block
from delprop.operators.schedule import assign
from delprop.operators.train import LOCAL_BYTES, Blocks, linearized_gradient
from delprop.scratch import stored
from delprop.spec import ModelSpec

#: Removed ids up to this number are broadcast; more are joined by a shuffle.
BROADCAST_IDS = 2_000_000
#: Captured sums up to this size go to the tasks of several removal sets.
BROADCAST_BYTES = 256 << 20

Sums = dict[int, tuple[int, Callable[[np.ndarray], np.ndarray], np.ndarray]]


def removed_rows(samples: DataFrame, removals: DataFrame, spec: ModelSpec, n: int) -> DataFrame:
    """The removed rows with their blocks; ids that do not exist do nothing, repeated ids count once."""
    ids = removals.select("sample_id").distinct()
    side = F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids
    if spec.schedule == "single":
        return assign(samples, spec, n).join(side, "sample_id", "left_semi")
    return assign(samples.join(side, "sample_id", "left_semi"), spec, n)


def _local_rows(blocked: DataFrame, m: int) -> Blocks:
    table = blocked.select("block_id", "sample_id", "features", F.col("label").cast("double").alias("label")).toArrow()
    if not table.num_rows:
        return {}
    table = table.sort_by([("block_id", "ascending"), ("sample_id", "ascending")])
    x, y = matrix_of(table.column("features"), m), table.column("label").to_numpy()
    return {b: (x[own], y[own]) for b, own in by_block(table.column("block_id").to_numpy())}


class Removed(dict):
    """Sums of the removed rows, by block (linear) or iteration (logistic): what is subtracted when the rows themselves are too many."""


def removed_share_of(capture: Capture, gone: DataFrame, local_bytes: int = LOCAL_BYTES) -> Blocks | Removed:
    """The removed rows in this process if they fit ``local_bytes``; else their aggregated sums, as many as were captured."""
    spec = capture.spec
    if gone.count() * (spec.m + 2) * 8 <= local_bytes:
        return _local_rows(gone, spec.m)
    if spec.kind == "linear":
        frame = block_gram(gone, spec.m)
    else:
        frame = iteration_sums(gone, spec, steps_of(spec, capture.n, spec.tau if capture.upto is None else capture.upto), capture.trajectory, capture.options)
    return Removed((r.block_id, _operator(r, spec.size)) for r in frame.toLocalIterator())


def _operator(r: Row, order: int) -> tuple[int, Callable[[np.ndarray], np.ndarray], np.ndarray]:
    if "values" in r:
        v, values = np.frombuffer(r.v).reshape(order, r.r), np.frombuffer(r["values"])
        return r.cnt, lambda w: v @ (values * (v.T @ w)), np.frombuffer(r.cross)
    if "r" in r:
        p, v = np.array(r.p).reshape(order, r.r), np.array(r.v).reshape(order, r.r)
        return r.cnt, lambda w: p @ (v.T @ w), np.array(r.cross)
    g = unpack(np.array(r.gram), order)
    return r.cnt, lambda w: g @ w, np.array(r.cross)


class Streamed:
    """Captured sums too large for this process: read in block order, one at a time, again for every pass over the blocks."""

    def __init__(self, frame: DataFrame, order: int) -> None:
        self.frame, self.order = stored(frame, "captured-sums").orderBy("block_id"), order
        self.rows: Iterator[Row] = iter(())
        self.held: Row | None = None
        self.at: int | None = None

    def get(self, block: int, default: tuple) -> tuple:
        if self.at is None or block < self.at:
            self.rows = self.frame.toLocalIterator()
            self.held = next(self.rows, None)
        self.at = block
        while self.held is not None and self.held.block_id < block:
            self.held = next(self.rows, None)
        return _operator(self.held, self.order) if self.held is not None and self.held.block_id == block else default


def captured_bytes(capture: Capture) -> int:
    """Upper estimate of the captured sums' size, without a job."""
    spec = capture.spec
    blocks = min(spec.blocks(capture.n), spec.tau) if spec.kind == "linear" else (spec.tau if capture.upto is None else capture.upto)
    size = spec.size
    rows = -(-capture.n // max(spec.blocks(capture.n), 1)) * (1 if spec.kind != "softmax" else spec.q)
    cells = packed_size(size) if capture.factors is None else 2 * size * min(size, 2 * rows)
    return 8 * blocks * (cells + size)


def load_sums(capture: Capture, local_bytes: int = LOCAL_BYTES) -> Sums | Streamed:
    """Captured sums as operators: in this process while they fit ``local_bytes``, else as a stream in the order of the iterations."""
    frame = capture.blocks if capture.factors is None else capture.factors
    if captured_bytes(capture) > local_bytes:
        return Streamed(frame, capture.spec.size)
    return {r.block_id: _operator(r, capture.spec.size) for r in frame.toLocalIterator()}


def removed_share(x: np.ndarray, y: np.ndarray, w: np.ndarray, at: np.ndarray, spec: ModelSpec, options: dict) -> np.ndarray:
    """The removed rows' part of C w + D (logistic), with pieces at the captured parameters ``at``."""
    if spec.kind == "binary":
        a, b = pieces(y * (x @ at), **options)
        return x.T @ (a * (x @ w) + b * y)
    slopes, offset = softmax_pieces(x @ at.reshape(spec.q, spec.m).T, **options)
    rest = -np.einsum("nij,nj->ni", (slopes + slopes.transpose(0, 2, 1)) / 2, x @ w.reshape(spec.q, spec.m).T) - offset
    rest[np.arange(len(y)), y.astype(int)] += 1
    return (rest.T @ x).ravel()


def run(capture: Capture, sums: Sums | Streamed, removed: Blocks | Removed, upto: int | None = None, coefficients: dict | None = None, first: int = 0, w: np.ndarray | None = None) -> np.ndarray:
    """The recurrence over iterations first..upto-1 (the captured ones by default) from parameters ``w`` (the start's by default).

    ``coefficients`` maps (block, t) to stored (a, b) of the removed rows; by
    default they are computed again from the trajectory.
    """
    spec, nb = capture.spec, capture.spec.blocks(capture.n)
    w = spec.start() if w is None else w
    for t in range(first, spec.tau if upto is None else upto):
        eta = spec.rate(t)
        count, apply, cross = sums.get(capture.block_of(t), (0, None, None))
        aggregated = isinstance(removed, Removed)
        gone = removed.get(capture.block_of(t) if aggregated else t % nb)
        left = count - (0 if gone is None else gone[0] if aggregated else len(gone[1]))
        shrunk = (1 - eta * spec.lam) * w
        if left <= 0:
            w = shrunk
            continue
        if spec.kind == "linear":
            move = cross - apply(w)
            if gone is not None:
                move = move - (gone[2] - gone[1](w) if aggregated else gone[0].T @ (gone[1] - gone[0] @ w))
            move = 2 * move
        else:
            move = apply(w) + cross
            if gone is not None and aggregated:
                move = move - gone[1](w) - gone[2]
            elif gone is not None:
                stored = None if coefficients is None else coefficients.get((t % nb, t))
                if stored is not None:
                    a, b = stored
                    move = move - gone[0].T @ (a * (gone[0] @ w) + b * gone[1])
                else:
                    move = move - removed_share(gone[0], gone[1], w, capture.trajectory[t], spec, capture.options)
        w = shrunk + eta / left * move
    return w


def replay(capture: Capture, samples: DataFrame, removals: DataFrame, coefficients: str = "recomputed", stored: DataFrame | None = None, local_bytes: int = LOCAL_BYTES) -> np.ndarray:
    """Parameters after the removal.  Dense or low-rank sums, linear, binary or softmax.

    Removed rows, their stored coefficients and the captured sums are each
    held in this process only while they fit ``local_bytes``: beyond it the
    removed rows are aggregated (with pieces computed again) and the sums streamed.
    """
    gone = removed_rows(samples, removals, capture.spec, capture.n)
    removed = removed_share_of(capture, gone, local_bytes)
    held = None
    if coefficients == "stored" and not isinstance(removed, Removed):
        ids = gone.select("sample_id", "block_id")
        table = stored.join(ids, "sample_id").orderBy("block_id", "t", "sample_id").collect()
        grouped: dict[tuple[int, int], list[tuple[float, float]]] = {}
        for r in table:
            grouped.setdefault((r.block_id, r.t), []).append((r.a, r.b))
        held = {k: (np.array([a for a, _ in v]), np.array([b for _, b in v])) for k, v in grouped.items()}
    return run(capture, load_sums(capture, local_bytes), removed, capture.upto, held)


def update(capture: Capture, samples: DataFrame, removals: DataFrame, earlier: DataFrame | None = None, **options) -> np.ndarray:
    """Deletions that accumulate: always the union of all removals against the original capture."""
    ids = removals.select("sample_id")
    if earlier is not None:
        ids = ids.unionByName(earlier.select("sample_id")).distinct()
    return replay(capture, samples, ids, **options)


def update_with_insertions(capture: Capture, samples: DataFrame, removals: DataFrame, added: DataFrame) -> np.ndarray:
    """Linear models: rows may also be added, since the sums are additive; added rows join the batch of their hash."""
    if capture.spec.kind != "linear":
        raise ValueError("insertion is exact for linear models only")
    gone = _local_rows(removed_rows(samples, removals, capture.spec, capture.n), capture.spec.m)
    new = _local_rows(assign(added, capture.spec, capture.n), capture.spec.m)
    sums = load_sums(capture)
    for b, (x, y) in new.items():
        count, apply, cross = sums.get(b, (0, lambda w: 0 * w, np.zeros(capture.spec.size)))
        sums[b] = (count + len(y), lambda w, f=apply, x=x: f(w) + x.T @ (x @ w), cross + x.T @ y)
    return run(capture, sums, gone)


def update_many(capture: Capture, samples: DataFrame, removals: DataFrame, local_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """(subset_id, w): one model a removal set, from one scan for all removed rows; sets run in parallel tasks.

    The captured sums are broadcast while they fit ``local_bytes``; beyond it
    the sets run one after the other over the streamed sums.
    """
    spec, n = capture.spec, capture.n
    if captured_bytes(capture) > local_bytes:
        return _update_each(capture, samples, removals, local_bytes)
    shipped = samples.sparkSession.sparkContext.broadcast(load_rows(capture))
    ids = removals.select("subset_id", "sample_id").distinct()
    side = F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids
    rows = assign(samples.join(side.select("sample_id").distinct(), "sample_id", "left_semi"), spec, n).join(side, "sample_id")
    # a set none of whose ids exist still gets its model
    marks = ids.select("subset_id").distinct().withColumn("block_id", F.lit(-1)).withColumn("sample_id", F.lit(None).cast("bigint"))
    marks = marks.withColumn("features", F.lit(None).cast("array<double>")).withColumn("label", F.lit(None).cast("double"))
    columns = ["subset_id", "block_id", "sample_id", "features", "label"]
    rows = rows.withColumn("label", F.col("label").cast("double")).select(*columns).unionByName(marks.select(*columns))

    bare = Capture(spec, n, None, None, capture.trajectory, capture.options, capture.upto)  # tasks need no tables

    def task(key: tuple[Any, ...], frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame[frame["block_id"] >= 0].sort_values(["block_id", "sample_id"])
        gone = {int(b): (np.array(g["features"].tolist(), float), g["label"].to_numpy(float)) for b, g in frame.groupby("block_id")}
        sums = {r.block_id: _operator(r, spec.size) for r in shipped.value}
        return pd.DataFrame({"subset_id": [key[0]], "w": [run(bare, sums, gone, bare.upto).tolist()]})

    kind = dict(removals.dtypes)["subset_id"]
    return rows.groupBy("subset_id").applyInPandas(task, f"subset_id {kind}, w array<double>")


def load_rows(capture: Capture) -> list[Row]:
    return (capture.blocks if capture.factors is None else capture.factors).collect()


def _update_each(capture: Capture, samples: DataFrame, removals: DataFrame, local_bytes: int) -> DataFrame:
    names = [r[0] for r in removals.select("subset_id").distinct().collect()]
    models = [(s, [float(v) for v in replay(capture, samples, removals.where(F.col("subset_id") == s), local_bytes=local_bytes)]) for s in names]
    return samples.sparkSession.createDataFrame(models, f"subset_id {dict(removals.dtypes)['subset_id']}, w array<double>")


def replay_survivors(blocks: Blocks, trajectory: np.ndarray, spec: ModelSpec, n_blocks: int, **options) -> np.ndarray:
    """The linearised rule over the survivors with pieces at the captured trajectory: what replay equals without subtraction."""
    w = spec.start()
    for t in range(spec.tau):
        eta, rows = spec.rate(t), blocks.get(t % n_blocks)
        shrunk = (1 - eta * spec.lam) * w
        w = shrunk if rows is None or not len(rows[1]) else shrunk - eta / len(rows[1]) * linearized_gradient(rows[0], rows[1], w, spec, trajectory[t], options)
    return w


def compose(capture: Capture, removed: Blocks, chunks: int, samples: DataFrame) -> np.ndarray:
    """Replay as composition of affine steps: each chunk of iterations folds to one (A, b) in its own task, then the chunks apply in order.

    Worth it only for few features and very many iterations.
    """
    spec, sums, nb = capture.spec, load_sums(capture), capture.spec.blocks(capture.n)
    size, identity = spec.size, np.eye(spec.size)
    capture = Capture(spec, capture.n, None, None, capture.trajectory, capture.options, capture.upto)  # tasks need no tables

    def step(t: int) -> tuple[np.ndarray, np.ndarray]:
        eta = spec.rate(t)
        count, apply, cross = sums.get(capture.block_of(t), (0, None, None))
        gone = removed.get(t % nb)
        left = count - (0 if gone is None else len(gone[1]))
        a = (1 - eta * spec.lam) * identity
        if left <= 0:
            return a, np.zeros(size)
        matrix = np.column_stack([apply(e) for e in identity])
        if spec.kind == "linear":
            if gone is not None:
                matrix, cross = matrix - gone[0].T @ gone[0], cross - gone[0].T @ gone[1]
            return a - 2 * eta / left * matrix, 2 * eta / left * cross
        if gone is not None:
            zero = removed_share(gone[0], gone[1], np.zeros(size), capture.trajectory[t], spec, capture.options)
            matrix = matrix - np.column_stack([removed_share(gone[0], gone[1], e, capture.trajectory[t], spec, capture.options) - zero for e in identity])
            cross = cross - zero
        return a + eta / left * matrix, eta / left * cross

    def task(key: tuple[Any, ...], frame: pd.DataFrame) -> pd.DataFrame:
        a, b = identity, np.zeros(size)
        for t in sorted(frame["t"]):
            na, nb_ = step(int(t))
            a, b = na @ a, na @ b + nb_
        return pd.DataFrame({"chunk": [key[0]], "a": [a.ravel().tolist()], "b": [b.tolist()]})

    frame = samples.sparkSession.range(spec.tau).select(F.col("id").alias("t"), F.floor(F.col("id") * chunks / spec.tau).cast("int").alias("chunk"))
    folded = frame.groupBy("chunk").applyInPandas(task, "chunk int, a array<double>, b array<double>").orderBy("chunk").collect()
    w = spec.start()
    for r in folded:
        w = np.array(r.a).reshape(size, size) @ w + np.array(r.b)
    return w

"""Sparse binary models: the survivors' rule is replayed directly, without factorisation or cached squares.

Rows are (sample_id, indices array<int>, values array<double>, label).  Blocks
of rows live in one process as flat index, value and row arrays while they fit
``local_bytes``; beyond it each iteration is one exploded aggregation.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from delprop.functions.linearize import coefficients_of, falling, pieces
from delprop.operators.schedule import assign
from delprop.scratch import stored
from delprop.spec import ModelSpec


@dataclass
class SparseBlock:
    row: np.ndarray
    index: np.ndarray
    value: np.ndarray
    y: np.ndarray
    ids: np.ndarray

    def times(self, w: np.ndarray) -> np.ndarray:
        return np.bincount(self.row, self.value * w[self.index], len(self.y))

    def gather(self, r: np.ndarray, m: int) -> np.ndarray:
        return np.bincount(self.index, self.value * r[self.row], m)

    def without(self, gone: np.ndarray) -> SparseBlock:
        keep = ~np.isin(self.ids, gone)
        number = np.cumsum(keep) - 1
        used = keep[self.row]
        return SparseBlock(number[self.row[used]], self.index[used], self.value[used], self.y[keep], self.ids[keep])


def load(samples: DataFrame, spec: ModelSpec, n: int, local_bytes: int = 1 << 30) -> dict[int, SparseBlock] | None:
    rows = assign(samples, spec, n)
    cells = rows.agg(F.sum(F.size("indices"))).first()[0] or 0
    if cells * 24 > local_bytes:
        return None
    out: dict[int, list] = {}
    for r in sorted(rows.select("block_id", "sample_id", "indices", "values", "label").collect(), key=lambda r: (r.block_id, r.sample_id)):
        out.setdefault(r.block_id, []).append(r)
    return {
        b: SparseBlock(
            np.repeat(np.arange(len(rs)), [len(r.indices) for r in rs]), np.concatenate([np.array(r.indices, np.int64) for r in rs]), np.concatenate([np.array(r["values"], float) for r in rs]),
            np.array([r.label for r in rs], float), np.array([r.sample_id for r in rs]),
        )
        for b, rs in out.items()
    }


def descend(blocks: dict[int, SparseBlock], spec: ModelSpec, n_blocks: int, coefficients: dict | None = None, capture: dict | None = None) -> np.ndarray:
    """Exact rule; with ``coefficients`` ((block, t) -> ids, a, b) the linearised rule; ``capture`` is filled with those of this run."""
    w = spec.start()
    for t in range(spec.tau):
        eta, rows = spec.rate(t), blocks.get(t % n_blocks)
        shrunk = (1 - eta * spec.lam) * w
        if rows is None or not len(rows.y):
            w = shrunk
            continue
        z = rows.times(w)
        if coefficients is not None:
            ids, a, b = coefficients[t % n_blocks, t]
            at = np.searchsorted(ids, rows.ids)
            factor = a[at] * z + b[at] * rows.y
        else:
            factor = rows.y * falling(rows.y * z)
        if capture is not None:
            a, b = pieces(rows.y * z)
            capture[t % n_blocks, t] = (rows.ids, a, b)
        w = shrunk + eta / len(rows.y) * rows.gather(factor, spec.m)
    return w


def replay_sparse(blocks: dict[int, SparseBlock], coefficients: dict, removed_ids: np.ndarray, spec: ModelSpec, n_blocks: int) -> np.ndarray:
    return descend({b: r.without(removed_ids) for b, r in blocks.items()}, spec, n_blocks, coefficients)


def margins(rows: DataFrame, w: np.ndarray) -> tuple[DataFrame, DataFrame]:
    """Cells (sample_id, label, index, v) of ``rows``, and (sample_id, label, z) with z = w.x; the parameters join on the index."""
    known = rows.sparkSession.createDataFrame([(i, float(w[i])) for i in np.flatnonzero(w).tolist()], "index int, w double")
    cells = rows.select("sample_id", "label", F.explode(F.arrays_zip("indices", "values")).alias("c")).select("sample_id", "label", F.col("c.indices").cast("int").alias("index"), F.col("c.values").alias("v"))
    return cells, cells.join(known, "index", "left").groupBy("sample_id", "label").agg(F.sum(F.col("v") * F.coalesce("w", F.lit(0.0))).alias("z"))


def gradient_jobs(rows: DataFrame, w: np.ndarray, coefficients: DataFrame | None = None) -> DataFrame:
    """(index, value): sum of label * f(label * w.x) * x over ``rows``, for blocks too large for one process; with ``coefficients`` (sample_id, a, b) of f's pieces."""
    cells, margin = margins(rows, w)
    if coefficients is None:
        factor = margin.select("sample_id", (F.col("label") / (1.0 + F.exp(F.col("label") * F.col("z")))).alias("f"))
    else:
        factor = margin.join(coefficients, "sample_id").select("sample_id", (F.col("a") * F.col("z") + F.col("b") * F.col("label")).alias("f"))
    return cells.join(factor, "sample_id").groupBy("index").agg(F.sum(F.col("v") * F.col("f")).alias("value"))


def descend_jobs(blocked: DataFrame, spec: ModelSpec, n_blocks: int, coefficients: dict[tuple[int, int], DataFrame] | None = None, capture: dict | None = None) -> np.ndarray:
    """As :func:`descend`, one exploded aggregation an iteration; this process holds the parameters only."""
    w = spec.start()
    counts = {r.block_id: r["count"] for r in blocked.groupBy("block_id").count().collect()}
    for t in range(spec.tau):
        eta, block = spec.rate(t), t % n_blocks
        shrunk = (1 - eta * spec.lam) * w
        if not counts.get(block):
            w = shrunk
            continue
        rows = blocked.where(F.col("block_id") == block)
        got = gradient_jobs(rows, w, None if coefficients is None else coefficients[block, t]).collect()
        if capture is not None:
            both = coefficients_of(F.col("label") * F.col("z"))
            capture[block, t] = stored(margins(rows, w)[1].select("sample_id", both.alias("c")).select("sample_id", "c.a", "c.b"), "pieces")
        w = shrunk
        index = np.array([r["index"] for r in got], np.int64)
        w[index] += eta / counts[block] * np.array([r["value"] for r in got])
    return w


def train(samples: DataFrame, spec: ModelSpec, n: int, capture: dict | None = None, local_bytes: int = 1 << 30) -> np.ndarray:
    """Parameters of a sparse model; ``capture`` is filled with the pieces' coefficients for :func:`replay`."""
    blocks, nb = load(samples, spec, n, local_bytes), spec.blocks(n)
    return descend_jobs(assign(samples, spec, n), spec, nb, capture=capture) if blocks is None else descend(blocks, spec, nb, capture=capture)


def replay(samples: DataFrame, removals: DataFrame, spec: ModelSpec, n: int, coefficients: dict, local_bytes: int = 1 << 30) -> np.ndarray:
    """Parameters without the removed rows, from the coefficients of the run with them."""
    nb = spec.blocks(n)
    blocks = load(samples, spec, n, local_bytes)
    if blocks is None:
        rest = assign(samples, spec, n).join(removals.select("sample_id").distinct(), "sample_id", "left_anti")
        return descend_jobs(rest, spec, nb, coefficients)
    return replay_sparse(blocks, coefficients, np.array([r.sample_id for r in removals.select("sample_id").distinct().collect()]), spec, nb)


def retrain(samples: DataFrame, removals: DataFrame, spec: ModelSpec, n: int, local_bytes: int = 1 << 30) -> np.ndarray:
    return train(samples.join(removals.select("sample_id").distinct(), "sample_id", "left_anti"), spec, n, None, local_bytes)

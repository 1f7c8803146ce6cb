"""Provenance capture: the per-iteration sums that an update subtracts from, in a constant number of Spark jobs.

Linear models: Gram and cross sums of each distinct block, independent of the
parameters.  Logistic models: C and D sums of each iteration, weighted by the
interpolant's pieces at that iteration's parameters; every row computes the
pieces of all iterations of its block in one pass, so capture is one job.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field
from typing import Any

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from delprop.functions.linearize import coefficients_of, pieces, softmax, softmax_pieces
from delprop.functions.sliding import sliding_grams
from delprop.functions.vector import array_of, dot, matrix_of, pack, packed_size, unpack
from delprop.operators.gram import FLUSH_BYTES, block_gram, by_block, summed
from delprop.operators.schedule import assign
from delprop.spec import ModelSpec

#: Largest order of a dense sum; beyond it only factors are kept.
MAX_DENSE = 2048
RANK_RULES = ("residual", "energy", "printed")
#: Factors as bytes of the kept eigenvalues and of their vectors.
EIGEN = "block_id int, cnt long, r int, cross binary, values binary, v binary"
#: Tasks that the iterations of few blocks are dealt to.
TASKS = 64


@dataclass
class Capture:
    """What training left behind.

    ``blocks``: (block_id, cnt, gram, cross), one row a block (linear) or an
    iteration (logistic).  ``factors``: the same with low-rank ``p``, ``v``.
    """

    spec: ModelSpec
    n: int
    blocks: DataFrame | None = None
    factors: DataFrame | None = None
    trajectory: np.ndarray = field(default_factory=lambda: np.zeros((0, 0)))
    options: dict = field(default_factory=dict)
    upto: int | None = None

    def block_of(self, t: int) -> int:
        """Row of ``blocks`` that iteration ``t`` uses."""
        return t % self.spec.blocks(self.n) if self.spec.kind == "linear" else t


def capture_linear(samples: DataFrame, spec: ModelSpec, n: int | None = None) -> Capture:
    n = samples.count() if n is None else n
    return Capture(spec, n, block_gram(assign(samples, spec, n), spec.m))


def piece_sums(x: np.ndarray, y: np.ndarray, w: np.ndarray, spec: ModelSpec, options: dict) -> tuple[np.ndarray, np.ndarray]:
    """C (dense, order ``spec.size``) and D of rows at parameters ``w``: minus the linearised gradient sum is C w + D."""
    if spec.kind == "binary":
        a, b = pieces(y * (x @ w), **options)
        return (x * a[:, None]).T @ x, x.T @ (b * y)
    logits = x @ w.reshape(spec.q, spec.m).T
    if options.get("method", "tangent") == "tangent":
        return _tangent_sums(x, y, logits, spec)
    slopes, offset = softmax_pieces(logits, **options)
    c = -np.einsum("nij,nk,nl->ikjl", slopes, x, x, optimize=True).reshape(spec.size, spec.size)
    rest = -offset
    rest[np.arange(len(y)), y.astype(int)] += 1
    return c, (rest.T @ x).ravel()


def _tangent_sums(x: np.ndarray, y: np.ndarray, logits: np.ndarray, spec: ModelSpec) -> tuple[np.ndarray, np.ndarray]:
    """One symmetric product a pair of classes: off the diagonal the parts are sums of p_i p_j x x', and the parts of a class add up to zero."""
    p = softmax(logits)

    def product(i: int, j: int) -> np.ndarray:
        z = x * np.sqrt(p[:, i] * p[:, j])[:, None]
        return z.T @ z

    return _of_pairs((product(i, j) for i, j in _pairs(spec.q)), spec), (_tangent_rest(y, logits, p).T @ x).ravel()


def _pairs(q: int) -> list[tuple[int, int]]:
    return [(i, j) for i in range(q) for j in range(i + 1, q)]


def _of_pairs(parts: Iterable[np.ndarray], spec: ModelSpec) -> np.ndarray:
    m, c = spec.m, np.zeros((spec.size, spec.size))
    for (i, j), part in zip(_pairs(spec.q), parts, strict=True):
        for a, b in ((i, j), (j, i)):
            c[a * m : (a + 1) * m, b * m : (b + 1) * m] = part
            c[a * m : (a + 1) * m, a * m : (a + 1) * m] -= part
    return c


def _tangent_rest(y: np.ndarray, logits: np.ndarray, p: np.ndarray) -> np.ndarray:
    rest = p * (logits - (p * logits).sum(1, keepdims=True)) - p
    rest[np.arange(len(y)), y.astype(int)] += 1
    return rest


def window_sums(stretches: Iterable[tuple[np.ndarray, np.ndarray, np.ndarray]], w: np.ndarray, spec: ModelSpec) -> tuple[int, np.ndarray, np.ndarray]:
    """(rows, C, D) of :func:`piece_sums` (softmax, tangent) over the windows of series: (values, labels, which windows count)."""
    series, weights, n, d = [], [], 0, np.zeros((spec.q, spec.m))
    left, right = np.array(_pairs(spec.q)).T
    for vals, y, own in stretches:
        x = np.ascontiguousarray(np.lib.stride_tricks.sliding_window_view(vals, spec.m)[: len(y)])
        logits = x @ w.reshape(spec.q, spec.m).T
        p = softmax(logits)
        d += (_tangent_rest(y, logits, p) * own[:, None]).T @ x
        series.append(vals)
        weights.append(p[:, left] * p[:, right] * own[:, None])
        n += int(own.sum())
    return n, _of_pairs(sliding_grams(series, weights, spec.m), spec), d.ravel()


def steps_of(spec: ModelSpec, n: int, upto: int) -> dict[int, list[int]]:
    """The iterations below ``upto`` that use each block."""
    nb = spec.blocks(n)
    return {b: list(range(b, upto, nb)) for b in range(min(nb, upto))}


def iteration_sums(rows: DataFrame, spec: ModelSpec, steps: dict[int, list[int]], trajectory: np.ndarray, options: dict) -> DataFrame:
    size = packed_size(spec.size)

    def partial(batch: pa.RecordBatch) -> Iterator[tuple[int, int, np.ndarray]]:
        x, y = matrix_of(batch.column("features"), spec.m), batch.column("label").to_numpy(zero_copy_only=False)
        for block, own in by_block(batch.column("block_id").to_numpy(zero_copy_only=False)):
            for t in steps.get(block, ()):
                c, d = piece_sums(x[own], y[own], trajectory[t], spec, options)
                # C is symmetric up to the interpolant's asymmetry (simplex pieces): both halves are averaged
                yield t, len(own), np.r_[pack((c + c.T) / 2), d]

    narrow = rows.select(F.col("block_id").cast("int").alias("block_id"), "features", F.col("label").cast("double").alias("label"))
    sums = summed(narrow, partial, size + spec.size)
    return sums.select("block_id", "cnt", F.slice("sums", 1, size).alias("gram"), F.slice("sums", size + 1, spec.size).alias("cross"))


def capture_logistic(samples: DataFrame, trajectory: np.ndarray, spec: ModelSpec, n: int | None = None, upto: int | None = None, **options) -> Capture:
    """C_t and D_t for t < ``upto`` (all iterations by default), keyed by iteration."""
    if spec.size > MAX_DENSE:
        raise ValueError(f"dense sums of order {spec.size} exceed {MAX_DENSE}; use capture_factors")
    n = samples.count() if n is None else n
    upto = spec.tau if upto is None else upto
    blocks = iteration_sums(assign(samples, spec, n), spec, steps_of(spec, n, upto), trajectory, options)
    return Capture(spec, n, blocks, trajectory=trajectory, options=options, upto=upto)


def capture_tail(samples: DataFrame, w: np.ndarray, spec: ModelSpec, **options) -> DataFrame:
    """One row: C and D over all rows with pieces frozen at parameters ``w``."""
    return iteration_sums(samples.withColumn("block_id", F.lit(0)), spec, {0: [0]}, w[None, :], options)


def stored_coefficients(samples: DataFrame, trajectory: np.ndarray, spec: ModelSpec, n: int, bound: float = 20.0, cells: int = 10**6) -> DataFrame:
    """(sample_id, t, a, b): slope and offset of every (row, iteration) of a binary model.

    The trajectory joins by iteration; it has ``tau`` rows of ``m`` doubles.
    """
    nb = spec.blocks(n)
    path = samples.sparkSession.createDataFrame([(t, t % nb, [float(v) for v in trajectory[t]]) for t in range(spec.tau)], "t int, block_id int, w array<double>")
    rows = assign(samples, spec, n).join(F.broadcast(path) if spec.tau * spec.m < 4_000_000 else path, "block_id")
    both = coefficients_of(F.col("label") * dot(F.col("features"), F.col("w")), bound, cells)
    return rows.select("sample_id", "t", both.alias("c")).select("sample_id", "t", "c.a", "c.b")


def rank_of(s: np.ndarray, eps: float, rule: str = "residual") -> int:
    """How many of the descending magnitudes ``s`` to keep.

    residual: the first dropped one is at most ``eps`` of the largest;
    energy: the dropped squares are at most ``eps`` squared of all;
    printed: the ratio of spectral norms of kept and whole, which is one for any rank.
    """
    if not len(s) or s[0] == 0:
        return 0
    if rule == "residual":
        return int((s > eps * s[0]).sum())
    if rule == "energy":
        left = np.r_[np.cumsum(s[::-1] ** 2)[::-1], 0.0] / (s**2).sum()
        return int(np.argmax(left <= eps**2))
    if rule == "printed":
        return 1
    raise ValueError(f"rank_rule must be one of {RANK_RULES}")


def factor(matrix: np.ndarray, eps: float, rule: str) -> tuple[np.ndarray, np.ndarray]:
    """P, V with matrix ~ P V', from the eigenpairs of largest magnitude."""
    values, vectors = np.linalg.eigh(matrix)
    order = np.argsort(-np.abs(values))
    keep = order[: rank_of(np.abs(values[order]), eps, rule)]
    return vectors[:, keep] * values[keep], vectors[:, keep]


def compress(capture: Capture, eps: float = 0.01, rank_rule: str = "residual") -> Capture:
    """The capture with rank-r factors in place of its symmetric sums: one small decomposition a block, in parallel."""
    order = capture.spec.size

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ps, vs, ranks = [], [], []
            for gram in matrix_of(batch.column("gram"), packed_size(order)) if batch.num_rows else ():
                p, v = factor(unpack(gram, order), eps, rank_rule)
                ps.append(p.ravel().tolist())
                vs.append(v.ravel().tolist())
                ranks.append(p.shape[1])
            if ranks:
                lists = pa.list_(pa.float64())
                yield pa.record_batch([batch.column("block_id"), batch.column("cnt"), batch.column("cross"), pa.array(ranks, pa.int32()), pa.array(ps, lists), pa.array(vs, lists)], ["block_id", "cnt", "cross", "r", "p", "v"])

    factors = capture.blocks.select("block_id", "cnt", "cross", "gram").mapInArrow(run, "block_id int, cnt long, cross array<double>, r int, p array<double>, v array<double>")
    return Capture(capture.spec, capture.n, None, factors, capture.trajectory, capture.options, capture.upto)


def _signed_rows(x: np.ndarray, y: np.ndarray, w: np.ndarray | None, spec: ModelSpec, options: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(rows, signs, D) with C = sum of sign * row' row over the rows of a block."""
    if spec.kind == "linear":
        return x, np.ones(len(x)), x.T @ y
    if spec.kind == "binary":
        a, b = pieces(y * (x @ w), **options)
        return x * np.sqrt(np.abs(a))[:, None], np.sign(a), x.T @ (b * y)
    slopes, offset = softmax_pieces(x @ w.reshape(spec.q, spec.m).T, **options)
    values, vectors = np.linalg.eigh((slopes + slopes.transpose(0, 2, 1)) / 2)
    rows = np.einsum("nij,nk->njik", vectors, x).reshape(-1, spec.size)
    rest = -offset
    rest[np.arange(len(y)), y.astype(int)] += 1
    return rows * np.sqrt(np.abs(values.ravel()))[:, None], -np.sign(values.ravel()), (rest.T @ x).ravel()


def _squeezed(rows: np.ndarray) -> np.ndarray:
    """At most as many rows as columns with the same rows' rows."""
    return np.linalg.qr(rows, mode="r") if len(rows) > rows.shape[1] else rows


def capture_factors(samples: DataFrame, spec: ModelSpec, n: int | None = None, trajectory: np.ndarray | None = None, eps: float = 0.01, rank_rule: str = "residual", fan_in: int = 32, **options) -> Capture:
    """Factors straight from the rows of each block, for more features than fit a dense sum.

    Every task squeezes its rows of a block to a triangular factor of at most
    ``size`` rows, apart for either sign; ``fan_in`` factors at a time meet in
    a task and are squeezed again, so no task holds a whole block and no
    order-``size`` square matrix is formed.
    """
    n = samples.count() if n is None else n
    nb, size = spec.blocks(n), spec.size
    steps = {b: [b] if spec.kind == "linear" else list(range(b, spec.tau, nb)) for b in range(nb)}
    schema = "block_id int, part int, cnt long, cross array<double>, plus array<double>, minus array<double>"
    empty = np.zeros((0, size))

    def record(t: int, part: int, held: list) -> pa.RecordBatch:
        lists = pa.list_(pa.float64())
        columns = [pa.array([t], pa.int32()), pa.array([part], pa.int32()), pa.array([held[0]], pa.int64()), *(pa.array([v.ravel().tolist()], lists) for v in held[1:])]
        return pa.record_batch(columns, ["block_id", "part", "cnt", "cross", "plus", "minus"])

    def join(held: list | None, count: int, cross: np.ndarray, plus: np.ndarray, minus: np.ndarray) -> list:
        held = [0, np.zeros(size), empty, empty] if held is None else held
        return [held[0] + count, held[1] + cross, _squeezed(np.concatenate([held[2], plus])), _squeezed(np.concatenate([held[3], minus]))]

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, held, cells = TaskContext.get().partitionId(), {}, 0
        for batch in batches:
            if not batch.num_rows:
                continue
            x, y = matrix_of(batch.column("features"), spec.m), batch.column("label").to_numpy(zero_copy_only=False)
            for block, own in by_block(batch.column("block_id").to_numpy(zero_copy_only=False)):
                for t in steps.get(block, ()):
                    rows, signs, cross = _signed_rows(x[own], y[own], None if trajectory is None else trajectory[t], spec, options)
                    before = 0 if t not in held else held[t][2].size + held[t][3].size
                    held[t] = join(held.get(t), len(own), cross, rows[signs > 0], rows[signs < 0])
                    cells += held[t][2].size + held[t][3].size - before
                    if cells * 8 > FLUSH_BYTES:
                        yield from (record(s, part, h) for s, h in held.items())
                        held, cells = {}, 0
        yield from (record(t, part, h) for t, h in held.items())

    def meet(key: tuple[Any, ...], table: pa.Table) -> pa.Table:
        held = None
        for r in table.to_pylist():
            held = join(held, r["cnt"], np.array(r["cross"]), np.array(r["plus"]).reshape(-1, size), np.array(r["minus"]).reshape(-1, size))
        return pa.Table.from_batches([record(key[0].as_py(), key[1].as_py(), held)])

    def factors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lists = pa.list_(pa.float64())
        for batch in batches:
            for r in batch.to_pylist():
                plus, minus = (np.array(r[c]).reshape(-1, size) for c in ("plus", "minus"))
                # signed low-rank form, through an orthonormal basis of the rows' space
                basis, tri = np.linalg.qr(np.concatenate([plus, minus]).T)
                values, vectors = np.linalg.eigh((tri * np.r_[np.ones(len(plus)), -np.ones(len(minus))]) @ tri.T)
                order = np.argsort(-np.abs(values))
                kept = order[: rank_of(np.abs(values[order]), eps, rank_rule)]
                v = basis @ vectors[:, kept]
                columns = [pa.array([r["block_id"]], pa.int32()), pa.array([r["cnt"]], pa.int64()), pa.array([r["cross"]], lists), pa.array([len(kept)], pa.int32()), pa.array([(v * values[kept]).ravel().tolist()], lists), pa.array([v.ravel().tolist()], lists)]
                yield pa.record_batch(columns, ["block_id", "cnt", "cross", "r", "p", "v"])

    rows = assign(samples, spec, n).select(F.col("block_id").cast("int").alias("block_id"), "features", F.col("label").cast("double").alias("label"))
    parts = rows.mapInArrow(partial, schema)
    # small sets have few partial factors: they meet at once
    for width in () if n * size * 8 <= 1 << 30 else (fan_in**2, fan_in):
        parts = parts.withColumn("part", F.pmod("part", F.lit(width))).groupBy("block_id", "part").applyInArrow(meet, schema)
    whole = parts.withColumn("part", F.lit(0)).groupBy("block_id", "part").applyInArrow(meet, schema)
    found = whole.mapInArrow(factors, "block_id int, cnt long, cross array<double>, r int, p array<double>, v array<double>")
    return Capture(spec, n, None, found, np.zeros((0, 0)) if trajectory is None else trajectory, options, spec.tau)


def capture_batches(samples: DataFrame, spec: ModelSpec, n: int, trajectory: np.ndarray | None = None, eps: float = 0.01, rank_rule: str = "residual", **options) -> Capture:
    """As :func:`capture_factors` for blocks that fit a task: one task an iteration (linear: a block) forms the dense sum and decomposes it.

    ``factors`` has the bytes of the kept eigenvalues and of their vectors.
    """
    if spec.size > MAX_DENSE:
        raise ValueError(f"dense sums of order {spec.size} exceed {MAX_DENSE}; use capture_factors")
    nb, linear = spec.blocks(n), spec.kind == "linear"
    units = min(nb, spec.tau) if linear else spec.tau

    def whole(key: tuple[Any, ...], table: pa.Table) -> pa.Table:
        t = key[0].as_py()
        x, y = matrix_of(table.column("features"), spec.m), table.column("label").to_numpy()
        return pa.Table.from_batches([_eigen_record(t, x, y, None if linear else trajectory[t], spec, eps, rank_rule, options)])

    rows = assign(samples, spec, n).select(F.col("block_id").cast("int").alias("block_id"), "features", F.col("label").cast("double").alias("label"))
    if not linear and spec.tau > nb:
        rows = rows.withColumn("block_id", F.explode(F.sequence(F.col("block_id"), F.lit(spec.tau - 1), F.lit(nb))))
    # rows are few and their work is not: a number of partitions that adaptive execution keeps
    rows = rows.repartition(min(4 * units, 200), "block_id")
    found = rows.groupBy("block_id").applyInArrow(whole, EIGEN)
    return Capture(spec, n, None, found, np.zeros((0, 0)) if trajectory is None else trajectory, options, spec.tau)


def _eigen_record(t: int, x: np.ndarray, y: np.ndarray, w: np.ndarray | None, spec: ModelSpec, eps: float, rank_rule: str, options: dict) -> pa.RecordBatch:
    """The kept eigenpairs of a batch's C, as one row of :data:`EIGEN`."""
    if spec.kind == "linear" and len(x) < spec.size and eps >= 1e-6:
        # fewer rows than columns: the eigenpairs of X'X come from those of XX'
        d = x.T @ y
        values, left = np.linalg.eigh(x @ x.T)
        keep = np.argsort(-values)
        keep = keep[: rank_of(np.maximum(values[keep], 0.0), eps, rank_rule)]
        vectors = x.T @ (left[:, keep] / np.sqrt(values[keep]))
    else:
        c, d = (x.T @ x, x.T @ y) if spec.kind == "linear" else piece_sums(x, y, w, spec, options)
        # the parts of a class add up to zero: nothing lies along equal parameters of all classes
        basis = _apart(spec.q) if spec.kind == "softmax" and options.get("method", "tangent") == "tangent" else np.eye(1)
        k, own = basis.shape
        c = np.einsum("ai,axby,bj->ixjy", basis, c.reshape(k, -1, k, spec.size // k), basis, optimize=True).reshape(own * spec.size // k, -1)
        values, vectors = np.linalg.eigh((c + c.T) / 2)
        keep = np.argsort(-np.abs(values))
        keep = keep[: rank_of(np.abs(values[keep]), eps, rank_rule)]
        vectors = np.einsum("ai,ixr->axr", basis, vectors[:, keep].reshape(own, -1, len(keep))).reshape(spec.size, -1)
    flat = [pa.array([v.tobytes()], pa.binary()) for v in (d, values[keep], vectors)]
    return pa.record_batch([pa.array([t], pa.int32()), pa.array([len(y)], pa.int64()), pa.array([len(keep)], pa.int32()), *flat], ["block_id", "cnt", "r", "cross", "values", "v"])


def _apart(q: int) -> np.ndarray:
    """(q x q-1): an orthonormal basis of the vectors whose entries add up to zero."""
    return np.linalg.qr(np.eye(q)[:, 1:] - 1 / q)[0]


def whole_blocks(blocked: DataFrame, spec: ModelSpec, n: int) -> DataFrame:
    """(block_id, x, y): the rows of each block as the bytes of its features, row by row, and of its labels; for blocks that fit a task."""

    def packed(table: pa.Table) -> pa.Table:
        x, y = matrix_of(table.column("features"), spec.m), table.column("label").to_numpy()
        return pa.table([table.column("block_id")[:1], *(pa.array([np.ascontiguousarray(v).tobytes()], pa.binary()) for v in (x, y))], ["block_id", "x", "y"])

    rows = blocked.select(F.col("block_id").cast("int").alias("block_id"), "features", F.col("label").cast("double").alias("label"))
    return rows.repartition(min(4 * min(spec.blocks(n), spec.tau), 200), "block_id").groupBy("block_id").applyInArrow(packed, "block_id int, x binary, y binary")


def window_factors(blocks: DataFrame, spec: ModelSpec, n: int, first: int, last: int, trajectory: np.ndarray | None = None, eps: float = 0.01, rank_rule: str = "residual", **options) -> DataFrame:
    """The ``factors`` of :func:`capture_batches` that iterations ``first`` to ``last`` - 1 use, from the table of :func:`whole_blocks`.

    ``trajectory`` has the parameters at these iterations only.  A block goes
    to as many tasks as its iterations may be dealt to, not once an iteration.
    """
    if spec.size > MAX_DENSE:
        raise ValueError(f"dense sums of order {spec.size} exceed {MAX_DENSE}; use capture_factors")
    nb, linear = spec.blocks(n), spec.kind == "linear"
    used = min(nb, last - first)
    parts = 1 if linear else min(-(-TASKS // used), -(-(last - first) // used))
    low, high = first % nb, (last - 1) % nb

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in range(batch.num_rows):
                x, y = (np.frombuffer(batch.column(c)[r].as_buffer()) for c in ("x", "y"))
                x, block, part = x.reshape(-1, spec.m), batch.column("block_id")[r].as_py(), batch.column("part")[r].as_py()
                for t in [block] if linear else range(first + (block - first) % nb, last, nb)[part::parts]:
                    yield _eigen_record(t, x, y, None if linear else trajectory[t - first], spec, eps, rank_rule, options)

    if used < nb:
        inside = (F.col("block_id") >= low, F.col("block_id") <= high)
        blocks = blocks.where(inside[0] & inside[1] if low <= high else inside[0] | inside[1])
    dealt = blocks.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))).repartition(min(4 * used * parts, 200), "block_id", "part")
    return dealt.mapInArrow(run, EIGEN)


def trajectory_frame(trajectory: np.ndarray, spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(t, [float(v) for v in w]) for t, w in enumerate(trajectory)], "t int, w array<double>")


def margins_at(samples: DataFrame, w: np.ndarray) -> DataFrame:
    return samples.withColumn("margin", F.col("label") * dot(F.col("features"), array_of(w)))

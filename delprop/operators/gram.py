"""Sums of outer products by block: the provenance that replay and the spectral update subtract from.

Three ways with equal results: native column sums for narrow rows, a long form
(one row a cell) for SQL users, and local BLAS on Arrow batches for wide rows,
whose partial sums then meet in a keyed sum (one small row a cell and task).
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from delprop.functions.vector import matrix_of, pack, packed_size

#: Bytes of partial sums a task holds before it hands them on.
FLUSH_BYTES = 256 << 20


def cells(features: Column, m: int) -> list[tuple[int, int, Column]]:
    return [(i, j, features[i] * features[j]) for i in range(m) for j in range(i, m)]


def native_gram(blocked: DataFrame, m: int, by: list[str] | None = None, weight: Column | None = None) -> DataFrame:
    """(by, cnt, gram, cross) by plain column sums; packed upper triangle."""
    by = ["block_id"] if by is None else by
    x, w = F.col("features"), F.lit(1) if weight is None else weight
    gram = F.array(*[F.sum(w * c) for _, _, c in cells(x, m)])
    cross = F.array(*[F.sum(F.col("label") * x[i]) for i in range(m)])
    return blocked.groupBy(*by).agg(F.count("*").alias("cnt"), gram.alias("gram"), cross.alias("cross"))


def long_gram(blocked: DataFrame, by: list[str] | None = None) -> DataFrame:
    """(by, i, j, value) for i <= j."""
    by = ["block_id"] if by is None else by
    left = blocked.select(*by, F.posexplode("features").alias("i", "x"), "features")
    both = left.select(*by, "i", "x", F.posexplode("features").alias("j", "y")).where("i <= j")
    return both.groupBy(*by, "i", "j").agg(F.sum(F.col("x") * F.col("y")).alias("value"))


def summed(frame: DataFrame, partial: Callable[[pa.RecordBatch], Iterator[tuple[int, int, np.ndarray]]], width: int) -> DataFrame:
    """(block_id, cnt, sums array<double>): ``partial`` yields (block, rows, vector of ``width``) from an Arrow batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}

        def emit() -> Iterator[pa.RecordBatch]:
            for block, (count, sums) in held.items():
                yield pa.record_batch([pa.array([block], pa.int32()), pa.array([count], pa.int64()), pa.array([sums.tolist()], pa.list_(pa.float64()))], ["block_id", "cnt", "part"])
            held.clear()

        for batch in batches:
            if not batch.num_rows:
                continue
            for block, count, sums in partial(batch):
                own = held.setdefault(block, [0, np.zeros(width)])
                own[0] += count
                own[1] += sums
            if len(held) * width * 8 > FLUSH_BYTES:
                yield from emit()
        yield from emit()

    parts = frame.mapInArrow(run, "block_id int, cnt long, part array<double>")
    # the count rides along as cell -1, so that each cell is summed in parallel
    cell = parts.select("block_id", F.posexplode(F.concat(F.array(F.col("cnt").cast("double")), "part")).alias("pos", "v"))
    totals = cell.groupBy("block_id", "pos").agg(F.sum("v").alias("v"))
    whole = totals.groupBy("block_id").agg(F.sort_array(F.collect_list(F.struct("pos", "v"))).alias("s"))
    values = F.transform("s", lambda x: x["v"])
    return whole.select("block_id", F.element_at(values, 1).cast("long").alias("cnt"), F.slice(values, 2, width).alias("sums"))


def by_block(blocks: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    order = np.argsort(blocks, kind="stable")
    cuts = np.flatnonzero(np.r_[True, np.diff(blocks[order]) != 0, True])
    for a, b in zip(cuts, cuts[1:], strict=False):
        yield int(blocks[order[a]]), order[a:b]


def arrow_gram(blocked: DataFrame, m: int) -> DataFrame:
    """(block_id, cnt, gram, cross) by BLAS on Arrow batches."""
    size = packed_size(m)

    def partial(batch: pa.RecordBatch) -> Iterator[tuple[int, int, np.ndarray]]:
        x, y = matrix_of(batch.column("features"), m), batch.column("label").to_numpy(zero_copy_only=False)
        for block, own in by_block(batch.column("block_id").to_numpy(zero_copy_only=False)):
            yield block, len(own), np.r_[pack(x[own].T @ x[own]), x[own].T @ y[own]]

    sums = summed(blocked.select(F.col("block_id").cast("int").alias("block_id"), "features", F.col("label").cast("double").alias("label")), partial, size + m)
    return sums.select("block_id", "cnt", F.slice("sums", 1, size).alias("gram"), F.slice("sums", size + 1, m).alias("cross"))


def block_gram(blocked: DataFrame, m: int, narrow: int = 12) -> DataFrame:
    return native_gram(blocked, m) if m <= narrow else arrow_gram(blocked, m)


def total_gram(samples: DataFrame, m: int, narrow: int = 12) -> DataFrame:
    return block_gram(samples.withColumn("block_id", F.lit(0)), m, narrow)


def sliced_grams(samples: DataFrame, m: int, keys: list[str], how: str = "cube") -> DataFrame:
    """Gram sums of every slice of the cube, rollup or plain grouping of ``keys``; null keys mean all."""
    grouped = {"cube": samples.cube, "rollup": samples.rollup, "plain": samples.groupBy}[how](*keys)
    x = F.col("features")
    return grouped.agg(
        *([F.grouping_id().alias("level")] if how != "plain" else []),
        F.count("*").alias("cnt"),
        F.array(*[F.sum(c) for _, _, c in cells(x, m)]).alias("gram"),
        F.array(*[F.sum(F.col("label") * x[i]) for i in range(m)]).alias("cross"),
    )


def leave_slice_out(samples: DataFrame, m: int, key: str) -> DataFrame:
    """For each value of ``key``: the sums of all other rows, as total minus slice."""
    slices = sliced_grams(samples, m, [key], "plain")
    total = samples.agg(
        F.count("*").alias("n"), F.array(*[F.sum(c) for _, _, c in cells(F.col("features"), m)]).alias("g"), F.array(*[F.sum(F.col("label") * F.col("features")[i]) for i in range(m)]).alias("c")
    )
    # the total is one row
    both = slices.crossJoin(F.broadcast(total))
    minus = lambda a, b: F.zip_with(a, b, lambda x, y: x - y)
    return both.select(key, (F.col("n") - F.col("cnt")).alias("cnt"), minus(F.col("g"), F.col("gram")).alias("gram"), minus(F.col("c"), F.col("cross")).alias("cross"))

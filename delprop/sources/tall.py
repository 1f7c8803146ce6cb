"""Sample sets of any number of rows as narrow tables: what can be derived (random columns, windows, copies) is made in the tasks that need it.

A set is stored once, as chunks of rows whose base features are squeezed apart
(so that flags and small domains take bits and bytes) or, for windows, as
stretches of values; every pass hands NumPy arrays to its function, in pieces
of a bounded number of rows, and Spark moves few rows with long bytes.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from delprop.functions.manyhash import uniforms, uniforms_of
from delprop.functions.vector import matrix_of
from delprop.operators.gram import summed
from delprop.scratch import settled, stored
from delprop.sources import features as fx
from delprop.sources.tables import lean_star, table

#: Windows in a stored stretch, rows in a stored chunk, and bytes of an Arrow batch of them; stretches summed at once.
STRETCH, CHUNK, BATCH_BYTES, GROUP = 1024, 4096, 4 << 20, 64

Take = Callable[[np.ndarray], tuple[np.ndarray, np.ndarray]]


@cache
def teachers(m: int, q: int) -> np.ndarray:
    """(m x q): the weights of every class."""
    return np.array([fx.teacher(m, c) for c in range(q)]).T


def planted(kind: str, ids: np.ndarray, x: np.ndarray, q: int = 1) -> np.ndarray:
    """The labels of :func:`features.with_label`."""
    return marked(kind, ids, x, q)[0]


def marked(kind: str, ids: np.ndarray, x: np.ndarray, q: int = 1) -> tuple[np.ndarray, np.ndarray]:
    """The labels, and whether the rows are for validation."""
    m = x.shape[1]
    salts = {"linear": [f"n{k}" for k in range(12)], "binary": ["logit"]}.get(kind) or [f"gumbel{c}" for c in range(q)]
    drawn = uniforms(ids, [*salts, "split"])
    u, valid = drawn[:, :-1], drawn[:, -1] < 0.1
    if kind == "linear":
        return x @ teachers(m, 1)[:, 0] + 0.1 * (u.sum(1) - 6.0), valid
    u = np.clip(u, 1e-9, 1 - 1e-9)
    if kind == "binary":
        return np.where(x @ teachers(m, 1)[:, 0] + np.log(u[:, 0] / (1.0 - u[:, 0])) >= 0, 1.0, -1.0), valid
    return (x @ teachers(m, q) - np.log(-np.log(u))).argmax(1).astype(float), valid


@dataclass
class Tall:
    """``form``: chunks (:func:`squeezed` bytes), windows (ids, vals) or arrays (features).  ``extra`` hash-random columns follow the stored ones; each row stands for ``copies``."""

    frame: DataFrame
    form: str
    kind: str
    m: int
    q: int = 1
    extra: int = 0
    copies: int = 1

    def bare(self) -> Tall:
        """For tasks, which need no table."""
        return Tall(None, self.form, self.kind, self.m, self.q, self.extra, self.copies)

    def pieces(self, batch: pa.RecordBatch) -> Iterator[tuple[np.ndarray, np.ndarray, Take]]:
        """(ids, is_valid, take): ``take`` gives features and labels of the rows at some places."""
        if not batch.num_rows:
            return
        if self.form == "windows":
            for ids, vals, labels, valid in _stretches(batch):
                x = np.lib.stride_tricks.sliding_window_view(vals, self.m)[: len(ids)]
                yield ids, valid, lambda own, x=x, labels=labels: (x[own], labels[own])
            return
        if self.form == "chunks":
            for body in batch.column("body"):
                chunk = pa.ipc.open_stream(body.as_buffer()).read_next_batch()
                ids, valid = (chunk.column(i).to_numpy(zero_copy_only=False) for i in range(2))
                yield ids, valid, lambda own, ids=ids, chunk=chunk: self._rows(ids, chunk, own)
            return
        ids, valid, labels = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("sample_id", "is_valid", "label"))
        base = matrix_of(batch.column("features"), self.m)
        yield ids, valid, lambda own: (base[own], labels[own])

    def _rows(self, ids: np.ndarray, chunk: pa.RecordBatch, own: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        stored_columns = self.m - self.extra
        first = chunk.num_columns - stored_columns
        x = np.empty((len(own), self.m))
        for i in range(stored_columns):
            x[:, i] = _plain(chunk.column(first + i), own)
        if not self.extra:
            return x, _plain(chunk.column(2), own).astype(float)
        x[:, stored_columns:] = 2.0 * uniforms(ids[own], [f"x{j}" for j in range(self.extra)]) - 1.0
        return x, planted(self.kind, ids[own], x, self.q)

    def ids_of(self, ids: np.ndarray) -> Iterator[np.ndarray]:
        """The ids of each copy of the rows."""
        yield from (ids * self.copies + c if self.copies > 1 else ids for c in range(self.copies))

    def count(self) -> int:
        """Training rows, copies included."""
        if self.form == "windows":
            n = self.frame.agg(F.sum(F.size(F.filter("valid", lambda v: ~v)))).first()[0]
        elif self.form == "chunks":
            n = self.frame.agg(F.sum("training")).first()[0]
        else:
            n = self.frame.where("not is_valid").count()
        return (n or 0) * self.copies

    def sums(self, partial: Callable[[np.ndarray, np.ndarray, Take], Iterator[tuple[int, int, np.ndarray]]], width: int) -> DataFrame:
        """As :func:`gram.summed`, over all rows; long vectors are summed within few tasks first."""
        own = self.bare()

        def run(batch: pa.RecordBatch) -> Iterator[tuple[int, int, np.ndarray]]:
            for ids, valid, take in own.pieces(batch):
                yield from partial(ids, valid, take)

        return self._summed(run, width)

    def window_sums(self, partial: Callable[[list[tuple[np.ndarray, ...]]], Iterator[tuple[int, int, np.ndarray]]], width: int) -> DataFrame:
        """As :meth:`sums` of windows: ``partial`` takes some stretches (values, labels, is_valid) at a time."""

        def run(batch: pa.RecordBatch) -> Iterator[tuple[int, int, np.ndarray]]:
            whole = [(vals, labels, valid) for _, vals, labels, valid in _stretches(batch)]
            for a in range(0, len(whole), GROUP):
                yield from partial(whole[a : a + GROUP])

        return self._summed(run, width)

    def dealt(self) -> DataFrame:
        """The stored rows in as many partitions as keep all cores busy."""
        tasks = 2 * self.frame.sparkSession.sparkContext.defaultParallelism
        return self.frame.coalesce(tasks) if self.frame.rdd.getNumPartitions() >= tasks else self.frame.repartition(tasks)

    def _summed(self, run: Callable[[pa.RecordBatch], Iterator[tuple[int, int, np.ndarray]]], width: int) -> DataFrame:
        # much work a row, and small files: few windows' files do not mean few tasks
        frame = self.dealt() if width > 50_000 else self.frame
        return summed(frame, run, width)


def _stretches(batch: pa.RecordBatch) -> Iterator[tuple[np.ndarray, ...]]:
    """(ids, vals, labels, valid) of each stretch."""
    for r in range(batch.num_rows):
        yield tuple(batch.column(c)[r].values.to_numpy(zero_copy_only=False) for c in ("ids", "vals", "labels", "valid"))


def squeezed(values: np.ndarray) -> pa.Array:
    """Doubles in few bytes and without loss: flags as bits, up to 256 values as bytes and a dictionary."""
    if ((values == 1.0) | ((values == 0.0) & ~np.signbit(values))).all():
        return pa.array(values == 1.0)
    words = pa.array(values.view(np.int64)).dictionary_encode()
    if len(words.dictionary) > 256:
        return pa.array(values)
    return pa.DictionaryArray.from_arrays(words.indices.cast(pa.uint8()), pa.array(words.dictionary.to_numpy().view(float)))


def _chunk(ids: np.ndarray, valid: np.ndarray, columns: list[np.ndarray]) -> bytes:
    """Rows of which some are read without the others' decoding; ``columns``: a label if it is stored, and the base features."""
    arrays = [pa.array(ids), pa.array(valid), *(squeezed(np.ascontiguousarray(c)) for c in columns)]
    batch, sink = pa.record_batch(arrays, [str(i) for i in range(len(arrays))]), pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, batch.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
        out.write_batch(batch)
    return sink.getvalue().to_pybytes()


def _plain(column: pa.Array, own: np.ndarray) -> np.ndarray:
    """A squeezed column's values at some places."""
    if isinstance(column, pa.DictionaryArray):
        return column.dictionary.to_numpy()[column.indices.to_numpy()[own]]
    return column.to_numpy(zero_copy_only=False)[own]


def tall(spark: SparkSession, folder: str, family: str, kind: str, m: int, q: int = 1, extra: int = 0, copies: int = 1) -> Tall:
    """The stored set of a workload's family: sgemm, higgs and covtype over the star, heartbeat over events, cifar10 over embeddings."""
    if family == "cifar10":
        return Tall(stored(fx.embedded(spark, folder, maps=m // 64), "workload"), "arrays", kind, m, q, 0, copies)
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))
    if family == "heartbeat":
        found = Tall(None, "windows", kind, m, q, 0, copies)

        def labelled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for r in range(batch.num_rows):
                    ids, vals = (batch.column(c)[r].values.to_numpy(zero_copy_only=False) for c in ("ids", "vals"))
                    x = np.lib.stride_tricks.sliding_window_view(vals, m)[: len(ids)]
                    row = [pa.array([v]) for v in (ids, vals, *marked(kind, ids, x, q))]
                    yield pa.record_batch(row, ["ids", "vals", "labels", "valid"])

        rows = fx.stretches(table(spark, folder, "events"), m, STRETCH)
        found.frame = stored(rows.mapInArrow(labelled, "ids array<bigint>, vals array<double>, labels array<double>, valid array<boolean>"), "workload")
        return found
    columns = {"sgemm": fx.eighteen_columns, "higgs": fx.twenty_eight_columns, "covtype": lambda: fx.fifty_four_columns(coded=True)}[family]()
    names = [f"c{i}" for i in range(len(columns))]

    def labelled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in (batch.slice(a, CHUNK) for a in range(0, batch.num_rows, CHUNK)):
                ids = part.column("sample_id").to_numpy()
                columns = [part.column(c).to_numpy(zero_copy_only=False) for c in names]
                y, valid = ([], uniforms_of(ids, "split") < 0.1) if extra else marked(kind, ids, np.column_stack(columns), q)
                columns = columns if extra else [y, *columns]
                yield pa.record_batch([pa.array([int((~valid).sum())], pa.int32()), pa.array([_chunk(ids, valid, columns)], pa.binary())], ["training", "body"])

    rows = lean_star(spark, folder, fx.part_codes()).select(fx.line_id().alias("sample_id"), *[c.cast("double").alias(k) for k, c in zip(names, columns, strict=True)])
    # the bytes are packed already; long rows want small groups
    options = {"compression": "none", "parquet.block.size": str(16 << 20)}
    found = Tall(stored(rows.mapInArrow(labelled, "training int, body binary"), "workload", **options), "chunks", kind, m, q, extra, copies)
    del rows
    settled(spark)  # the joins' shuffle files are as large as the set
    return found

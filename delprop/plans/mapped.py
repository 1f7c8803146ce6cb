"""Rows that updates and retraining work on, in files of this process's own scratch folder: mapped, so that their number is not bound by its memory."""

from __future__ import annotations

import os
import tempfile
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from delprop.functions.manyhash import uniforms
from delprop.operators.train import Blocks
from delprop.scratch import LONG_ROWS, settled, stored
from delprop.sources.tall import Tall
from delprop.spec import ModelSpec

#: Bytes of the vectors of some rows: block, class, id, features row by row, label.
PICKED = "touched boolean, a binary, b binary, c binary, d binary, e binary"
KINDS = (np.int32, np.int32, np.int64, np.float64, np.float64)
TOUCHED = "sample_id bigint, features array<double>, label double, block_id int"
#: Bytes of rows handled at once.
PART_BYTES = 4 << 20
#: Bytes that come to the driver before its JVM collects what came by.
SETTLE_BYTES = 128 << 20


def classes(ids: np.ndarray, rates: list[float]) -> np.ndarray:
    """The place of the least of the ascending ``rates`` at which a row is removed; their number if it never is."""
    return np.searchsorted(np.array(rates), uniforms(ids, ["rm"])[:, 0], side="right")


def pick(tall: Tall, spec: ModelSpec, n: int, rates: list[float]) -> DataFrame:
    """The training rows that some iteration touches (block_id >= 0) or some rate removes (cls < number of rates), from one pass over all rows."""
    own, batches = tall.bare(), spec.batches(n)
    some = max(1, PART_BYTES // (8 * spec.m))

    def run(frames: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in frames:
            for ids, valid, take in own.pieces(batch):
                train = np.flatnonzero(~valid)
                for copy in own.ids_of(ids[train]):
                    hashed = uniforms(copy, [spec.seed, "rm"])
                    block = np.floor(hashed[:, 0] * batches).astype(np.int32)
                    block[block >= spec.tau] = -1
                    cls = np.searchsorted(np.array(rates), hashed[:, 1], side="right").astype(np.int32)
                    for kept, touched in ((np.flatnonzero(block >= 0), True), (np.flatnonzero((block < 0) & (cls < len(rates))), False)):
                        for part in (kept[a : a + some] for a in range(0, len(kept), some)):
                            x, y = take(train[part])
                            flat = (np.ascontiguousarray(v, kind).tobytes() for v, kind in zip((block[part], cls[part], copy[part], x, y), KINDS, strict=True))
                            yield pa.record_batch([pa.array([touched]), *(pa.array([v], pa.binary()) for v in flat)], ["touched", *"abcde"])

    return stored((tall.dealt() if tall.extra else tall.frame).mapInArrow(run, PICKED), "picked", **LONG_ROWS)


class Mapped:
    """Touched rows by block, those that go first last within a block; and the removed rows by class."""

    def __init__(self, picked: DataFrame, m: int, rates: int) -> None:
        self.folder = tempfile.TemporaryDirectory(prefix="delprop-rows-")
        self.m, self.rates = m, rates
        labels: list[list[np.ndarray]] = [[] for _ in range(rates)]
        out = {c: open(self._path(c), "wb") for c in ("raw", "place", "ids", "labels", *range(rates))}
        for block, cls, ids, x, y in _arrived(picked, m):
            at = block >= 0
            place = block[at].astype(np.int64) * (rates + 1) + (rates - cls[at])
            for name, values in (("raw", x[at]), ("place", place), ("ids", ids[at]), ("labels", y[at])):
                out[name].write(values.tobytes())
            for c in np.unique(cls[cls < rates]):
                out[c].write(x[cls == c].tobytes())
                labels[c].append(y[cls == c])
        for f in out.values():
            f.close()
        self.gone = [(self._map(c), np.concatenate(v) if v else np.zeros(0)) for c, v in enumerate(labels)]
        place, raw = self._map("place", np.int64, 1).ravel(), self._map("raw")
        order = np.lexsort((self._map("ids", np.int64, 1).ravel(), place))
        step = max(1, PART_BYTES // (8 * m))
        with open(self._path("touched"), "wb") as f:
            for a in range(0, len(order), step):
                f.write(raw[order[a : a + step]].tobytes())
        self.x, self.y = self._map("touched"), np.asarray(self._map("labels", np.float64, 1).ravel()[order])
        place = np.asarray(place[order])
        self.block, self.cls = (place // (rates + 1)).astype(np.int32), (rates - place % (rates + 1)).astype(np.int16)
        del order, raw, place
        for name in ("raw", "place", "ids", "labels"):
            os.remove(self._path(name))
        cuts = np.flatnonzero(np.r_[True, np.diff(self.block) != 0, True]) if len(self.block) else np.zeros(1, int)
        self.spans = {int(self.block[a]): (int(a), int(b)) for a, b in zip(cuts, cuts[1:], strict=False)}

    def _path(self, name: object) -> str:
        return os.path.join(self.folder.name, str(name))

    def _map(self, name: object, kind: type = np.float64, width: int | None = None) -> np.ndarray:
        path, width = self._path(name), width or self.m
        return np.memmap(path, kind, "r").reshape(-1, width) if os.path.getsize(path) else np.zeros((0, width), kind)

    def scratch(self, rows: int, width: int) -> np.ndarray:
        """An array that is in a file, too; the last one's place is used again."""
        self.held = np.memmap(self._path("scratch"), np.float64, "w+", shape=(rows, width))
        return self.held

    def split(self, rate: int, factor: float = 1.0) -> tuple[Blocks, Blocks]:
        """(left, gone) of every touched block at a rate; removed rows are scaled by ``factor``."""
        left, gone = {}, {}
        for b, (a, e) in self.spans.items():
            cut = a + int((self.cls[a:e] > rate).sum())
            left[b] = (self.x[a:cut], self.y[a:cut])
            if cut < e:
                gone[b] = (self.x[cut:e] * factor, self.y[cut:e])
        return left, gone

    def removed(self, rate: int, factor: float = 1.0) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """All removed rows at a rate, in parts."""
        step = max(1, PART_BYTES // (8 * self.m))
        for x, y in self.gone[: rate + 1]:
            for a in range(0, len(y), step):
                yield x[a : a + step] * factor if factor != 1.0 else x[a : a + step], y[a : a + step]

    def removed_count(self, rate: int) -> int:
        return sum(len(y) for _, y in self.gone[: rate + 1])

    def close(self) -> None:
        self.gone, self.x = [], np.zeros((0, self.m))
        self.folder.cleanup()


class Whole(dict):
    """Touched blocks with the rows that go, joined one block at a time."""

    def __init__(self, left: Blocks, gone: Blocks) -> None:
        super().__init__(left)
        self.gone = gone

    def get(self, block: int, default: object = None) -> object:
        rows, more = super().get(block, default), self.gone.get(block)
        return rows if rows is None or more is None else (np.concatenate([rows[0], more[0]]), np.concatenate([rows[1], more[1]]))


def _arrived(picked: DataFrame, m: int) -> Iterator[tuple[np.ndarray, ...]]:
    """(block, cls, ids, x, y) in batches as the tasks packed them, one partition at a time in this process."""
    came = 0
    for r in picked.select(*"abcde").toLocalIterator():
        came += sum(map(len, r))
        if came > SETTLE_BYTES:
            settled(picked.sparkSession)
            came = 0
        yield _vectors(r, m)
    settled(picked.sparkSession)


def _vectors(r: Sequence[bytes], m: int) -> tuple[np.ndarray, ...]:
    block, cls, ids, x, y = (np.frombuffer(v, kind) for v, kind in zip(r, KINDS, strict=True))
    return block, cls, ids, x.reshape(-1, m), y


def touched(picked: DataFrame, m: int, rate: int, factor: float = 1.0) -> DataFrame:
    """(sample_id, features, label, block_id) of the rows that some iteration touches, removed ones scaled by ``factor``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in zip(*(batch.column(c) for c in "abcde"), strict=True):
                block, cls, ids, x, y = _vectors([v.as_buffer() for v in r], m)
                x = x if factor == 1.0 else np.where((cls <= rate)[:, None], x * factor, x)
                lists = pa.ListArray.from_arrays(np.arange(0, x.size + 1, m, dtype=np.int32), x.ravel())
                yield pa.record_batch([pa.array(ids), lists, pa.array(y), pa.array(block)], ["sample_id", "features", "label", "block_id"])

    return picked.where("touched").mapInArrow(run, TOUCHED)

"""Document quality by gated-attention multiple-instance learning.

A document is a bag of passages (lines, long lines cut every
``PASSAGE_BYTES``).  Every passage is encoded by writing-style statistics and
a small hidden layer; a gated attention (tanh gate times sigmoid gate) learnt
from document labels alone weighs the passages; the weighted representation
is scored by a logistic layer.  Gradients are written out and follow Adam.

Edge cases: null, empty or blank texts have one empty passage; null ids count
as held out; rows with null labels are not learnt from; with no learnable
rows every score is the base rate 0.5; repeated rows stay rows; extra columns
are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from delprop.llm.bytescan import SPACE, buffers, runs, word_hashes
from delprop.llm.common import held_out, labelled_sample, map_arrow

PASSAGE_BYTES = 2000
#: Byte classes whose shares describe a passage.
_CLASSES = ["ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz", "0123456789", ".,;:", "!?", "#$%&*", "|<>{}[]\\/=+_~^", "\"'`()-@"]
_CLASS = np.full(256, len(_CLASSES), np.int64)
for _k, _letters in enumerate(_CLASSES):
    _CLASS[np.frombuffer(_letters.encode(), np.uint8)] = _k
_CLASS[128:] = len(_CLASSES) + 1
WIDTH = len(_CLASSES) + 2 + 8


def passages(texts: list[str | None]) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, row of each passage in the run, passage features)."""
    for first, data, begins in buffers(texts):
        size, last = len(data), np.r_[begins[1:], len(data)]
        lines = np.flatnonzero(data == 10) + 1
        cuts = np.unique(np.r_[begins, lines[lines < size], *([np.arange(0)] if size < PASSAGE_BYTES else [_long_cuts(begins, lines, size)])])
        n = len(cuts)
        piece = np.repeat(np.arange(n), np.diff(np.r_[cuts, size]))
        counts = np.bincount(piece * (len(_CLASSES) + 2) + _CLASS[data], minlength=n * (len(_CLASSES) + 2)).reshape(n, -1)
        starts, ends = runs(~SPACE[data])
        of = piece[starts] if len(starts) else starts
        words = np.bincount(of, minlength=n)
        hashes = word_hashes(data, starts, ends)
        same = np.r_[False, (hashes[1:] == hashes[:-1]) & (of[1:] == of[:-1])] if len(starts) else np.zeros(0, bool)
        again = np.bincount(of, same, n)
        row = np.searchsorted(begins, cuts, "right") - 1
        word_row = row[of] if len(of) else of
        order = np.lexsort((hashes, word_row))
        first_seen = np.r_[True, (hashes[order][1:] != hashes[order][:-1]) | (word_row[order][1:] != word_row[order][:-1])] if len(starts) else np.zeros(0, bool)
        distinct = np.bincount(word_row[order], first_seen, len(begins))
        in_row = np.bincount(word_row, minlength=len(begins))
        # words whose last byte is a mark other than a sentence mark, and words that are marks only
        tail = np.isin(_CLASS[data[ends - 1]], (5, 6)) if len(starts) else same
        lone = (ends - starts == 1) & (_CLASS[data[starts]] == 6) if len(starts) else same
        shout = (_CLASS[data[ends - 1]] == 4) if len(starts) else same
        total = np.maximum(counts.sum(1), 1)
        safe = np.maximum(words, 1)
        lengths = last - begins
        columns = [
            *(counts[:, k] / total for k in range(counts.shape[1])),
            again / safe,
            (distinct / np.maximum(in_row, 1))[row],
            np.bincount(of, tail, n) / safe,
            np.bincount(of, lone, n) / safe,
            np.bincount(of, shout, n) / safe,
            np.log1p(words),
            np.log1p(lengths)[row],
            counts[:, 0] / np.maximum(counts[:, 0] + counts[:, 1], 1),
        ]
        filled = words > 0
        filled |= np.bincount(row, filled, len(begins))[row] == 0  # a blank document keeps its passages
        yield first, row[filled], np.column_stack(columns)[filled]


def _long_cuts(begins: np.ndarray, lines: np.ndarray, size: int) -> np.ndarray:
    edges = np.unique(np.r_[begins, lines, size])
    long = np.flatnonzero(np.diff(edges) > PASSAGE_BYTES)
    return np.concatenate([np.arange(edges[i], edges[i + 1], PASSAGE_BYTES) for i in long.tolist()] or [np.zeros(0, np.int64)])


@dataclass
class AttentionModel:
    """Encoder (tanh layer), gated attention, logistic head; inputs standardised by ``mean`` and ``scale``."""

    mean: np.ndarray
    scale: np.ndarray
    parts: dict[str, np.ndarray]

    def encode(self, x: np.ndarray) -> np.ndarray:
        return np.clip((x - self.mean) / self.scale, -8, 8)

    def forward(self, x: np.ndarray, row: np.ndarray, n: int) -> dict[str, np.ndarray]:
        """``row`` is sorted and every row 0..n-1 has a passage."""
        p = self.parts
        h = np.tanh(x @ p["w"] + p["w0"])
        t, s = np.tanh(h @ p["v"]), 1 / (1 + np.exp(-(h @ p["u"])))
        e = (t * s) @ p["a"]
        at = np.searchsorted(row, np.arange(n))
        weight = np.exp(e - np.maximum.reduceat(e, at)[row])
        weight /= np.add.reduceat(weight, at)[row]
        bag = np.add.reduceat(weight[:, None] * h, at, axis=0)
        z = bag @ p["c"] + p["c0"][0]
        return {"h": h, "t": t, "s": s, "weight": weight, "bag": bag, "chance": 1 / (1 + np.exp(-z))}

    def gradient(self, x: np.ndarray, row: np.ndarray, y: np.ndarray) -> dict[str, np.ndarray]:
        p, f = self.parts, self.forward(x, row, len(y))
        dz = (f["chance"] - y) / len(y)
        dbag = dz[:, None] * p["c"]
        dh = f["weight"][:, None] * dbag[row]
        dweight = (dbag[row] * f["h"]).sum(1)
        mean = np.add.reduceat(f["weight"] * dweight, np.searchsorted(row, np.arange(len(y))))
        de = f["weight"] * (dweight - mean[row])
        dt = de[:, None] * p["a"] * f["s"] * (1 - f["t"] ** 2)
        ds = de[:, None] * p["a"] * f["t"] * f["s"] * (1 - f["s"])
        dh += dt @ p["v"].T + ds @ p["u"].T
        dpre = dh * (1 - f["h"] ** 2)
        return {
            "w": x.T @ dpre, "w0": dpre.sum(0), "v": f["h"].T @ dt, "u": f["h"].T @ ds,
            "a": (f["t"] * f["s"]).T @ de, "c": f["bag"].T @ dz, "c0": np.array([dz.sum()]),
        }

    def score(self, texts: list[str | None]) -> np.ndarray:
        out = np.zeros(len(texts))
        for first, row, x in passages(texts):
            n = int(row[-1]) + 1
            out[first : first + n] = self.forward(self.encode(x), row, n)["chance"]
        return out


def fit(texts: list[str], labels: np.ndarray, hidden: int = 24, gate: float = 12, turns: int = 40, batch: int = 256, rate: float = 5e-3, decay: float = 1e-4, seed: int = 5) -> AttentionModel:
    draw = np.random.default_rng(seed)
    gate = int(gate)
    shapes = {"w": (WIDTH, hidden), "w0": (hidden,), "v": (hidden, gate), "u": (hidden, gate), "a": (gate,), "c": (hidden,), "c0": (1,)}
    parts = {k: draw.normal(0, 0.3, s) if k not in ("w0", "c0") else np.zeros(s) for k, s in shapes.items()}
    if not len(texts) or labels.min() == labels.max():
        parts["c"] *= 0
        return AttentionModel(np.zeros(WIDTH), np.ones(WIDTH), parts)
    runs_ = [(row + first, x) for first, row, x in passages(texts)]
    row, x = np.concatenate([r for r, _ in runs_]), np.concatenate([x for _, x in runs_])
    model = AttentionModel(x.mean(0), np.maximum(x.std(0), 1e-3), parts)
    x, y = model.encode(x), labels.astype(float)
    bounds = np.searchsorted(row, np.arange(len(texts) + 1))
    m, v, step = {k: np.zeros_like(p) for k, p in parts.items()}, {k: np.zeros_like(p) for k, p in parts.items()}, 0
    total = turns * -(-len(texts) // batch)
    for _ in range(turns):
        order = draw.permutation(len(texts))
        for at in range(0, len(order), batch):
            chosen = order[at : at + batch]
            sizes = bounds[chosen + 1] - bounds[chosen]
            index = np.concatenate([np.arange(bounds[i], bounds[i + 1]) for i in chosen.tolist()])
            grads = model.gradient(x[index], np.repeat(np.arange(len(chosen)), sizes), y[chosen])
            step += 1
            pace = rate * (1 - step / (total + 1))
            for k, g in grads.items():
                g = g + decay * parts[k]
                m[k] = 0.9 * m[k] + 0.1 * g
                v[k] = 0.999 * v[k] + 0.001 * g * g
                parts[k] -= pace * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.999**step)) + 1e-8)
    return model


def train(documents: DataFrame, labels: DataFrame, target: str = "quality", sample_rows: int = 6000) -> AttentionModel:
    """Fit on at most about ``sample_rows`` labelled rows that are not held out; each text counts once."""
    rows = labelled_sample(documents, labels, target, sample_rows).select("text", "label").collect()
    unique = dict(sorted((r.text, r.label) for r in rows))
    return fit(list(unique), np.array(list(unique.values())))


def score(documents: DataFrame, model: AttentionModel, threshold: float = 0.3) -> DataFrame:
    """(doc_id, held_out, score, predicted) for every row of ``documents``."""
    rows = documents.select(F.col("doc_id").cast("long").alias("doc_id"), held_out(F.col("doc_id")).alias("held_out"), "text")

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        chance = model.score(batch.column("text").to_pylist())
        columns = [batch.column("doc_id"), batch.column("held_out"), pa.array(chance), pa.array((chance >= threshold).astype(np.int32))]
        return pa.record_batch(columns, ["doc_id", "held_out", "score", "predicted"])

    return map_arrow(rows, kernel, "doc_id long, held_out boolean, score double, predicted int")

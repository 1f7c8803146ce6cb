"""Toxicity by multiple-instance learning: sentence scores combined by noisy-or.

A document is a bag of sentences.  A sentence's chance of being offensive is
logistic in its marks: the words it holds and their first bytes, so that an
offensive stem counts under any ending; the document is toxic unless every
sentence is harmless, so P = 1 - prod(1 - p).  Only document labels are known:
weights are learnt through the noisy-or, with a small rate of wrong labels in
the likelihood and an L1 penalty that leaves weight on few marks.  The sentence
chances then locate the offending sentences.

Words are maximal runs of letters.  Marks are hashed to ``1 << BITS`` slots; a
prefix shares the slot of the word it spells.

Edge cases: null, empty or wordless texts have no sentences and score 0; null
ids count as held out; rows with null labels are not learnt from; with no
learnable rows every score is 0; repeated rows stay rows; extra columns are
ignored (:func:`keep_clean` keeps them); an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from delprop.llm.bytescan import LETTER, STOP, buffers, prefix_hashes, runs, word_hashes
from delprop.llm.common import held_out, keep_rows, labelled_sample, map_arrow

BITS = 20
#: Bytes of the prefixes that count as marks besides the whole word.
PREFIXES = (4, 5, 6)
#: Rate of wrong labels in the likelihood.
WRONG = 0.04


def bags(texts: list[str | None]) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(first row, row of each sentence, sentence of each mark, slot of each mark, (start, end) byte of each sentence) per run of texts.

    Sentences are numbered, and rows and bytes counted, within the run.
    """
    for first, data, begins in buffers(texts):
        starts, ends = runs(LETTER[data])
        if not len(starts):
            continue
        raw = np.cumsum(STOP[data], dtype=np.int32)[starts]
        change = np.r_[True, raw[1:] != raw[:-1]]
        fresh, sentence = np.flatnonzero(change), np.cumsum(change) - 1
        rows = np.searchsorted(begins, starts[fresh], "right") - 1
        marks, owners = [word_hashes(data, starts, ends)], [sentence]
        for longer, hashes in prefix_hashes(data, starts, ends, PREFIXES):
            marks.append(hashes)
            owners.append(sentence[longer])
        slots = (np.concatenate(marks) >> np.uint64(64 - BITS)).astype(np.int64)
        yield first, rows, np.concatenate(owners), slots, np.c_[starts[fresh], ends[np.r_[fresh[1:] - 1, len(ends) - 1]]]


@dataclass
class NoisyOr:
    weights: np.ndarray
    bias: float

    def hazards(self, sentence: np.ndarray, slots: np.ndarray, count: int) -> np.ndarray:
        """-log(1 - p) of each sentence."""
        z = self.bias + np.bincount(sentence, self.weights[slots], count)
        return np.logaddexp(0.0, z)

    def score(self, texts: list[str | None]) -> np.ndarray:
        out = np.zeros(len(texts))
        for first, rows, sentence, slots, _ in bags(texts):
            total = np.bincount(rows, self.hazards(sentence, slots, len(rows)))
            out[first : first + len(total)] = -np.expm1(-total)
        return out

    def offending(self, text: str, least: float = 0.5) -> list[tuple[int, int, float]]:
        """(start byte, end byte, chance) of the sentences at or above ``least``."""
        out = []
        for _, rows, sentence, slots, spans in bags([text]):
            chance = -np.expm1(-self.hazards(sentence, slots, len(rows)))
            out += [(int(spans[k, 0]), int(spans[k, 1]), float(chance[k])) for k in np.flatnonzero(chance >= least).tolist()]
        return out


def fit(texts: list[str], labels: np.ndarray, turns: int = 600, rate: float = 0.3, penalty: float = 1e-4, least_documents: int = 8, least_z: float = 6.0) -> NoisyOr:
    """Proximal Adagrad on the noisy-or likelihood.

    Only marks in at least ``least_documents`` sample texts, and so much more
    frequent among the toxic ones that their two-proportion z is ``least_z``,
    can get weight; sentences without such a mark differ by nothing and are
    counted, not listed.
    """
    model = NoisyOr(np.zeros(1 << BITS, np.float32), -30.0)
    if not len(texts) or labels.min() == labels.max():
        return model
    y, n = labels.astype(float), len(texts)
    # texts that hold each slot, and toxic ones among them, run by run: a text lies within one run
    sentences, times, hits = np.zeros(n), np.zeros(1 << BITS, np.int32), np.zeros(1 << BITS, np.float32)
    for first, rows, sentence, slots, _ in bags(texts):
        pairs = np.unique((rows[sentence] + first) << BITS | slots)
        slot, mark = pairs & ((1 << BITS) - 1), y[pairs >> BITS]
        times += np.bincount(slot, minlength=1 << BITS).astype(np.int32)
        hits += np.bincount(slot, mark, 1 << BITS).astype(np.float32)
        np.add.at(sentences, rows + first, 1)
    base = y.mean()
    with np.errstate(invalid="ignore", divide="ignore"):
        z = (hits - times * base) / np.sqrt(times * base * (1 - base))
    known = np.flatnonzero((times >= least_documents) & (z >= least_z))
    number = np.full(1 << BITS, -1, np.int32)
    number[known] = np.arange(len(known))
    doc_of, sent_of, word_of, offset = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], 0
    for first, rows, sentence, slots, _ in bags(texts):
        used = number[slots] >= 0
        pair = np.unique(sentence[used] << BITS | number[slots[used]].astype(np.int64))
        fresh, own = np.unique(pair >> BITS, return_inverse=True)
        doc_of.append(rows[fresh] + first)
        sent_of.append(own + offset)
        word_of.append(pair & ((1 << BITS) - 1))
        offset += len(fresh)
    doc, sent, word = map(np.concatenate, (doc_of, sent_of, word_of))
    bare = sentences - np.bincount(doc, minlength=n)
    theta, bias = np.full(len(known), 8.0), -8.0  # every screened mark starts as suspect: from zero the likelihood is flat
    squares, square = np.full(len(known), 1e-6), 1e-6
    for _ in range(turns):
        z = bias + np.bincount(sent, theta[word], len(doc))
        total = np.bincount(doc, np.logaddexp(0.0, z), n) + bare * np.logaddexp(0.0, bias)
        clear = np.exp(-total)
        p = WRONG + (1 - 2 * WRONG) * (1 - clear)
        slope = ((1 - y) / (1 - p) - y / p) * (1 - 2 * WRONG) * clear / n
        each = slope[doc] / (1 + np.exp(-z))
        grad = np.bincount(word, each[sent], len(known))
        grad_bias = each.sum() + (slope * bare).sum() / (1 + np.exp(-bias))
        squares += grad**2
        square += grad_bias**2
        step = rate / np.sqrt(squares)
        theta -= step * grad
        theta = np.maximum(theta - step * penalty, 0)
        bias -= rate * grad_bias / np.sqrt(square)
    model.weights[known] = theta
    model.bias = float(bias)
    return model


def train(documents: DataFrame, labels: DataFrame, target: str = "toxic", sample_rows: int = 8000) -> NoisyOr:
    """Fit on at most about ``sample_rows`` labelled rows that are not held out; each text counts once."""
    rows = labelled_sample(documents, labels, target, sample_rows).select("text", "label").collect()
    unique = dict(sorted((r.text, r.label) for r in rows))
    return fit(list(unique), np.array(list(unique.values())))


def score(documents: DataFrame, model: NoisyOr, threshold: float = 0.5) -> DataFrame:
    """(doc_id, held_out, score, predicted) for every row of ``documents``."""
    rows = documents.select(F.col("doc_id").cast("long").alias("doc_id"), held_out(F.col("doc_id")).alias("held_out"), "text")

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        chance = model.score(batch.column("text").to_pylist())
        columns = [batch.column("doc_id"), batch.column("held_out"), pa.array(chance), pa.array((chance >= threshold).astype(np.int32))]
        return pa.record_batch(columns, ["doc_id", "held_out", "score", "predicted"])

    return map_arrow(rows, kernel, "doc_id long, held_out boolean, score double, predicted int")


def keep_clean(documents: DataFrame, model: NoisyOr, threshold: float = 0.5) -> DataFrame:
    """The rows of ``documents`` whose score is below ``threshold``, with all their columns."""
    return keep_rows(documents, lambda texts: (model.score(texts) < threshold).tolist())

"""Benchmark decontamination by template canonicalisation.

Words lose case and surrounding marks; numbers, names (capitalised words
inside a sentence) and units after numbers become typed placeholders.  Every
window of ``width`` such tokens of every document is hashed (rolling, whole
batches at once) and joined with the hashed windows of the benchmark items.
Windows that meet are aligned token by token with the item: words must be
equal where they are literal, and placeholders must map the item's values to the document's
one to one, so a question asked again with other numbers or names is caught
while a coincidence of placeholders is not.  A document is contaminated by an
item when an aligned stretch covers ``least_tokens`` tokens, or the whole item
if that is shorter.  Windows that are mostly placeholders (tables, arithmetic,
lists of names) say too little as templates; they are hashed on the words
themselves and aligned by equal words, so verbatim copies of such passages are
found as well, while copies of them with other values are not.

The benchmark's windows are the hash join's built side.  They go to the
workers in blocks of at most ``block_windows`` windows (a checked size); a
larger benchmark makes further passes over the documents.

Edge cases: null or blank texts match nothing; null ids stay (as null); items
shorter than ``width`` tokens and without three literal ones match nothing; repeated rows are
judged each; extra columns are ignored (:func:`keep_clean` keeps them); empty
tables give an empty result.
"""

from __future__ import annotations

from collections import deque
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from delprop.llm.bytescan import SPACE, buffers, runs, word_hashes
from delprop.llm.common import keep_rows, map_arrow, union_all

NUMBER, NAME, UNIT = (np.uint64(k) for k in (1, 2, 3))
# Units of measure that count as such after a number: fixed values.
UNITS = ["%", "percent", "mm", "cm", "m", "km", "in", "inch", "inches", "ft", "feet", "mile", "miles", "mg", "g", "kg", "lb", "lbs", "pounds", "ounces", "ml", "l", "liters", "litres", "s", "sec", "seconds", "min", "minutes", "h", "hours", "days", "weeks", "months", "years", "dollars", "cents", "euros", "usd", "eur", "degrees", "mph", "kmh", "volts", "watts", "meters", "metres", "grams", "apples", "points"]
_ALNUM = np.array([48 <= b <= 57 or 65 <= b <= 90 or 97 <= b <= 122 or b >= 128 for b in range(256)])
_DIGIT = np.array([48 <= b <= 57 for b in range(256)])
_UPPER = np.array([65 <= b <= 90 for b in range(256)])
_CLOSE = np.array([b in b".!?:" for b in range(256)])
_STEP = 0xD6E8FEB86659FD93
#: Keeps windows of words apart from windows of templates.
_EXACT = np.uint64(0x9E3779B97F4A7C15)


def _hash_of(words: list[str]) -> np.ndarray:
    data = np.frombuffer(" ".join(words).encode() + b" ", np.uint8)
    return word_hashes(data, *runs(~SPACE[data]))


_UNIT_HASHES = np.sort(_hash_of(UNITS))


@dataclass
class Tokens:
    """Canonical tokens of a run of texts: row, template code, hash of the word itself."""

    row: np.ndarray
    code: np.ndarray
    word: np.ndarray


def canonical(data: np.ndarray, begins: np.ndarray) -> Tokens:
    starts, ends = runs(~SPACE[data])
    solid = np.flatnonzero(_ALNUM[data])
    first, last = np.searchsorted(solid, starts), np.searchsorted(solid, ends) - 1
    closes = np.zeros(len(starts), bool) if not len(starts) else _CLOSE[data[ends - 1]]
    used = np.flatnonzero(first <= last)
    a, b = solid[first[used]], solid[last[used]] + 1
    row = np.searchsorted(begins, starts[used], "right") - 1
    word = word_hashes(data, a, b)
    upper = np.r_[0, np.cumsum(_UPPER[data])]
    capital = _UPPER[data[a]] & (upper[b] - upper[a] == 1) & (b - a > 1)
    number = _DIGIT[data[a]]
    # a word opens a sentence if the text begins there or the chunk before it closes one
    opens = np.r_[True, closes[:-1]][used] if len(used) else np.zeros(0, bool)
    opens |= np.r_[True, row[1:] != row[:-1]] if len(row) else opens
    unit = np.r_[False, number[:-1]] & (row == np.r_[-1, row[:-1]]) if len(row) else number
    if len(row):
        at = np.minimum(np.searchsorted(_UNIT_HASHES, word), len(_UNIT_HASHES) - 1)
        unit &= _UNIT_HASHES[at] == word
    code = np.where(number, NUMBER, np.where(unit, UNIT, np.where(capital & ~opens, NAME, word | np.uint64(4))))
    return Tokens(row, code, word)


def _window_sums(values: np.ndarray, at: np.ndarray, width: int) -> np.ndarray:
    out, step = np.zeros(len(at), np.uint64), np.uint64(1)
    for k in range(width):
        out += values[at + k] * step
        step = np.uint64(int(step) * _STEP % (1 << 64))
    return out


def _mixed(sums: np.ndarray) -> np.ndarray:
    sums = sums ^ (sums >> np.uint64(33))
    return sums * np.uint64(0xFF51AFD7ED558CCD)


def windows(tokens: Tokens, width: int, item: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(position, hash, on words) of every window of ``width`` tokens of one text.

    Windows at least half of whose tokens are literal are hashed as templates, the others on their words.
    An ``item``'s first token may turn out a placeholder inside a document: where that decides, its window is hashed both ways.
    """
    n = len(tokens.code) - width + 1
    if n <= 0:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, bool)
    sums, literal = np.zeros(n, np.uint64), np.zeros(n, np.int16)
    step = np.uint64(1)
    for k in range(width):
        part = tokens.code[k : k + n]
        sums += part * step
        literal += part > UNIT
        step = np.uint64(int(step) * _STEP % (1 << 64))
    whole = tokens.row[:n] == tokens.row[width - 1 :]
    at = np.flatnonzero(whole & (literal * 2 >= width))
    if item:
        literal[0] -= tokens.code[0] > UNIT
    exact = np.flatnonzero(whole & (literal * 2 < width))
    hashes = np.r_[_mixed(sums[at]), _mixed(_window_sums(tokens.word, exact, width) ^ _EXACT)]
    return np.r_[at, exact], hashes, np.arange(len(hashes)) >= len(at)


@dataclass
class Item:
    item_id: object
    code: np.ndarray
    word: np.ndarray


class TemplateIndex:
    """Sorted window hashes of a block of items, by window width, behind a bit filter."""

    BITS = 20

    def __init__(self, items: list[Item], width: int) -> None:
        self.items = items
        self.by_width: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = {}
        groups: dict[int, list[int]] = {}
        for i, item in enumerate(items):
            if len(item.code) >= width or (item.code > UNIT).sum() >= 3:
                groups.setdefault(min(width, len(item.code)), []).append(i)
        for w, members in groups.items():
            hashes, owners, places = [], [], []
            for i in members:
                at, h, _ = windows(Tokens(np.zeros(len(items[i].code), np.int64), items[i].code, items[i].word), w, item=True)
                hashes.append(h)
                owners.append(np.full(len(h), i))
                places.append(at)
            h, o, p = (np.concatenate(x) for x in (hashes, owners, places))
            order = np.argsort(h, kind="stable")
            seen = np.zeros(1 << self.BITS, bool)
            seen[(h >> np.uint64(64 - self.BITS)).astype(np.int64)] = True
            self.by_width[w] = (h[order], o[order], p[order], seen)

    def matches(self, tokens: Tokens, least_tokens: int) -> list[tuple[int, int, int, int, int]]:
        """(row, item, first token, covered tokens, changed slots) of every contaminated (row, item), once each."""
        best: dict[tuple[int, int], tuple[int, int, int]] = {}
        for w, (hashes, owners, places, seen) in self.by_width.items():
            at, h, exact = windows(tokens, w)
            maybe = seen[(h >> np.uint64(64 - self.BITS)).astype(np.int64)]
            at, h, exact = at[maybe], h[maybe], exact[maybe]
            low, high = np.searchsorted(hashes, h, "left"), np.searchsorted(hashes, h, "right")
            lines: set[tuple[int, int, int, bool]] = set()
            for i in np.flatnonzero(low < high).tolist():
                for j in range(low[i], high[i]):
                    lines.add((int(tokens.row[at[i]]), int(owners[j]), int(at[i] - places[j]), bool(exact[i])))
            for row, item, shift, on_words in sorted(lines):
                first, covered, changed = self._aligned(tokens, row, item, shift, on_words)
                key = (row, item)
                if covered >= min(least_tokens, len(self.items[item].code)) and covered > best.get(key, (0, 0, 0))[1]:
                    best[key] = (first, covered, changed)
        return [(row, item, *value) for (row, item), value in sorted(best.items())]

    def _aligned(self, tokens: Tokens, row: int, item: int, shift: int, on_words: bool) -> tuple[int, int, int]:
        """Longest stretch on one diagonal with equal words, or equal templates and a one-to-one mapping of slot values."""
        target = self.items[item]
        start, stop = max(0, -shift), min(len(target.code), len(tokens.code) - shift)
        own = slice(start + shift, stop + shift)
        same = (tokens.word[own] == target.word[start:stop]) & (tokens.row[own] == row)
        if not on_words:
            same |= (tokens.code[own] == target.code[start:stop]) & (tokens.row[own] == row)
        begin = int(np.searchsorted(tokens.row, row))
        best = (0, 0, 0)
        for a, b in zip(*runs(same), strict=True):
            # slot value -> (its partner, the last place it was seen)
            forward: dict[int, tuple[int, int]] = {}
            backward: dict[int, tuple[int, int]] = {}
            changed: deque[int] = deque()
            left = a
            for k in range(a, b):
                if target.code[start + k] <= UNIT:
                    x, y = int(target.word[start + k]), int(tokens.word[start + shift + k])
                    cut = left
                    for partner, last, due in ((*forward.get(x, (y, -1)), y), (*backward.get(y, (x, -1)), x)):
                        if partner != due:
                            cut = max(cut, last + 1)
                    if cut > left:
                        # go on just after the slot that conflicts: what follows it agrees with this one
                        best = max(best, (int(k - left), int(start + shift + left - begin), len(changed)))
                        left = cut
                        while changed and changed[0] < left:
                            changed.popleft()
                    forward[x], backward[y] = (y, k), (x, k)
                    if x != y:
                        changed.append(k)
            best = max(best, (int(b - left), int(start + shift + left - begin), len(changed)))
        return best[1], best[0], best[2]


def read_items(benchmark: DataFrame) -> list[Item]:
    """Canonical items; the benchmark is the small side and is read whole by the driver."""
    out = []
    for item_id, text in benchmark.select("item_id", "text").distinct().collect():
        for _, data, begins in buffers([text]):
            tokens = canonical(data, begins)
            out.append(Item(item_id, tokens.code, tokens.word))
    return sorted(out, key=lambda i: (i.item_id is None, i.item_id))


def _blocks(items: list[Item], block_windows: int) -> Iterator[list[Item]]:
    held, size = [], 0
    for item in items:
        held.append(item)
        size += len(item.code)
        if size >= block_windows:
            yield held
            held, size = [], 0
    if held:
        yield held


def contaminated(documents: DataFrame, benchmark: DataFrame, width: int = 8, least_tokens: int = 13, block_windows: int = 2_000_000) -> DataFrame:
    """(doc_id, item_id, covered_tokens, item_tokens, first_token, changed_slots): one row per contaminated document row and item."""
    rows = documents.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    schema = "doc_id long, item_id long, covered_tokens int, item_tokens int, first_token int, changed_slots int"
    found = []
    for items in _blocks(read_items(benchmark), block_windows):
        index = TemplateIndex(items, width)

        def kernel(batch: pa.RecordBatch, index: TemplateIndex = index) -> pa.RecordBatch:
            out: list[tuple] = []
            ids = batch.column("doc_id").to_pylist()
            for first, data, begins in buffers(batch.column("text").to_pylist()):
                for row, item, at, covered, changed in index.matches(canonical(data, begins), least_tokens):
                    target = index.items[item]
                    out.append((ids[first + row], target.item_id, covered, len(target.code), at, changed))
            names = [f.split()[0] for f in schema.split(", ")]
            columns = list(zip(*out, strict=True)) or [()] * 6
            return pa.record_batch([pa.array(c, pa.int64() if i < 2 else pa.int32()) for i, c in enumerate(columns)], names)

        found.append(map_arrow(rows, kernel, schema))
    return union_all(found) if found else documents.sparkSession.createDataFrame([], schema)


def keep_clean(documents: DataFrame, benchmark: DataFrame, width: int = 8, least_tokens: int = 13, block_windows: int = 2_000_000) -> DataFrame:
    """The rows of ``documents`` that no item contaminates, with all their columns."""
    out = documents
    for items in _blocks(read_items(benchmark), block_windows):
        index = TemplateIndex(items, width)

        def judge(texts: list[str | None], index: TemplateIndex = index) -> list[bool]:
            clean = [True] * len(texts)
            for first, data, begins in buffers(texts):
                for row, *_ in index.matches(canonical(data, begins), least_tokens):
                    clean[first + row] = False
            return clean

        out = keep_rows(out, judge)
    return out

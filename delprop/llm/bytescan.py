"""Vectorised reading of many texts at once: words, their hashes, and segment boundaries, over one byte buffer."""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np

#: Odd multiplier of the polynomial word hash, and its inverse modulo 2^64.
_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)

#: Texts are joined until a buffer holds about this many bytes.
BUFFER = 1 << 18
#: Bytes hashed at a time.
BLOCK = 1 << 19


def _table(pick) -> np.ndarray:
    return np.array([pick(b) for b in range(256)])


LOWER = _table(lambda b: b + 32 if 65 <= b <= 90 else b).astype(np.uint8)
LETTER = _table(lambda b: 65 <= b <= 90 or 97 <= b <= 122 or b >= 128)
SPACE = _table(lambda b: b in b" \t\n\r\x0b\x0c")
STOP = _table(lambda b: b in b".!?\n")


@lru_cache(maxsize=1)
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    out = []
    for base in (_BASE, _INVERSE):
        powers = np.full(n, base, np.uint64)
        powers[0] = 1
        out.append(np.cumprod(powers))
    return out[0], out[1]


def buffers(texts: list[str | None]) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, bytes, start of each row) for successive runs of texts; every text is followed by a line feed."""
    first, held, size = 0, [], 0
    for i, text in enumerate(texts):
        raw = (text or "").encode("utf-8", "surrogatepass") + b"\n"
        held.append(raw)
        size += len(raw)
        if size >= BUFFER or i == len(texts) - 1:
            lengths = np.fromiter(map(len, held), np.int64, len(held))
            yield first, np.frombuffer(b"".join(held), np.uint8), np.cumsum(lengths) - lengths
            first, held, size = i + 1, [], 0


def runs(member: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the maximal runs of true values."""
    edge = np.diff(member.astype(np.int8), prepend=0, append=0)
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)


def _mixed(sums: np.ndarray) -> np.ndarray:
    sums = sums ^ (sums >> np.uint64(31))
    sums *= np.uint64(0xBF58476D1CE4E5B9)
    return sums ^ (sums >> np.uint64(29))


def _polynomials(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Polynomial of each slice of ``data``, which holds at most ``BLOCK`` bytes."""
    up, down = _powers(BLOCK)
    sums = np.zeros(len(data) + 1, np.uint64)
    np.cumsum((LOWER[data].astype(np.uint64) + np.uint64(1)) * up[: len(data)], out=sums[1:])
    return (sums[ends] - sums[starts]) * down[starts]


def _long_polynomial(data: np.ndarray) -> np.uint64:
    total = 0
    for at in range(0, len(data), BLOCK):
        part = data[at : at + BLOCK]
        own = int(_polynomials(part, np.zeros(1, np.int64), np.array([len(part)]))[0])
        total += own * pow(_BASE, at, 1 << 64)
    return np.uint64(total % (1 << 64))


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of the slices, ASCII case ignored; slices come in order and working memory is bounded whatever their lengths."""
    out = np.empty(len(starts), np.uint64)
    i = 0
    while i < len(starts):
        low = starts[i]
        j = int(np.searchsorted(ends, low + BLOCK, "right"))
        if j > i:
            out[i:j] = _polynomials(data[low : ends[j - 1]], starts[i:j] - low, ends[i:j] - low)
        else:  # one slice longer than a block
            out[i], j = _long_polynomial(data[low : ends[i]]), i + 1
        i = j
    return _mixed(out)


def prefix_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, lengths: tuple[int, ...]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(slices longer than a length, hashes of their first bytes) for each of the growing ``lengths``; a prefix hashes as the word it spells."""
    up, _ = _powers(BLOCK)
    chosen, sums, done = np.arange(len(starts)), np.zeros(len(starts), np.uint64), 0
    for length in lengths:
        longer = ends[chosen] - starts[chosen] > length
        chosen, sums = chosen[longer], sums[longer]
        for k in range(done, length):
            sums = sums + (LOWER[data[starts[chosen] + k]].astype(np.uint64) + np.uint64(1)) * up[k]
        done = length
        yield chosen, _mixed(sums)

"""Mixture-controlled packing by deficit round-robin at token granularity.

Every source is a queue of its documents' tokens.  Each window of ``length``
tokens serves every queue its share; what rounding denies a queue is its
deficit and is carried to the next window, so after any number of windows a
queue is within a token of its entitlement.  Queues with less than a token a
window are served about ``quantum`` tokens at a time, likewise by deficits.
Because entitlements are linear, the tokens that queue ``s`` has been served after ``w`` windows are a
closed form, and so are the tokens of the queues before it: the window and the
offset of any token follow from its position in its queue alone, in constant
time whatever the number of queues, and deficits carry across partitions
without a sequential pass.  Positions come from per-partition subtotals and
their prefix sums.

Without targets a queue's share is its share of all tokens, and every window
but the last is full and in proportion.  With targets, shares hold until a
queue runs dry; the remaining queues with a target then divide the window by
their targets (at most two further phases of the same form a target).  Sources
without a target follow when all targets have run dry, in proportion to their tokens.

Documents are tokenised once, in the partition that reads them; ids are kept
as two-byte numbers in the shared scratch folder and cut there, so texts and
ids are never shuffled.  The driver holds one number a source.

Edge cases: a null text counts as empty (its one token is the end mark); a null
source is a queue of its own; every source has an exact queue, however many
there are; targets of sources that have no rows count for nothing; a null
doc_id stays null; repeated rows are documents of their own; an
empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import json
import unicodedata
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from delprop.llm.bytescan import LOWER, SPACE, runs, word_hashes
from delprop.llm.common import WORKER_CACHES, bound_batches, map_arrow, materialise, release_worker_memory

#: Bytes of text that are tokenised at a time.
SEGMENT = 1 << 18
#: Chunks of more bytes are tokenised each time they occur.
LONGEST = 64
_PIECES = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+")
#: Chunks of other characters than these go to the tokenizer whole: its reading of them is not repeated here.
_PLAIN = regex.compile(r"[!-~\u00a1-\u012f\u0131-\u017f]+")
#: Bytes of chunks that are merged many at a time: ASCII without the apostrophe, and the two-byte Latin letters.
_SIMPLE = np.array([33 <= b <= 126 and b != 39 or 128 <= b <= 191 or 195 <= b <= 197 for b in range(256)])
#: Two-byte characters among them that are no letters or do not keep their length in lower case.
_NOT_SIMPLE = ["×", "÷", "İ"]
#: Byte classes of pieces: line feed, letter, digit, other.
_KIND = np.array([0 if b == 10 else 1 if 97 <= b <= 122 or b >= 128 else 2 if 48 <= b <= 57 else 3 for b in range(256)], np.int8)


def _byte_letters() -> list[str]:
    """The byte-level vocabulary's letter for each byte: printable bytes stand for themselves, the rest follow from 256 up."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    others = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(others)) for b in range(256)]


class ChunkTable:
    """Open-addressed table from (hash, check word) to token ids, in flat arrays of bounded size; full, it starts anew.

    The check word holds a chunk's length and last bytes, so that a chunk takes another's ids only if both 64-bit words agree.
    """

    def __init__(self, dtype: np.dtype, bits: int = 20) -> None:
        self.bits, self.most = bits, 1 << (bits - 1)
        self.dtype = dtype
        self.clear()

    def clear(self) -> None:
        self.hashes = np.zeros(1 << self.bits, np.uint64)
        self.checks = np.zeros(1 << self.bits, np.uint64)
        self.number = np.full(1 << self.bits, -1, np.int32)
        self.first, self.size = np.zeros(1 << 12, np.int64), np.zeros(1 << 12, np.int64)
        self.ids = np.zeros(1 << 14, self.dtype)
        self.n = self.used = 0

    def add(self, ids: np.ndarray, sizes: np.ndarray) -> np.ndarray:
        """Numbers of new entries that hold ``ids``, so many each."""
        n, used = self.n + len(sizes), self.used + len(ids)
        if n > len(self.first):
            self.first, self.size = (np.concatenate([x, np.zeros(n, np.int64)]) for x in (self.first, self.size))
        if used > len(self.ids):
            self.ids = np.concatenate([self.ids, np.zeros(used, self.dtype)])
        self.first[self.n : n], self.size[self.n : n] = self.used + np.cumsum(sizes) - sizes, sizes
        self.ids[self.used : used] = ids
        out = np.arange(self.n, n)
        self.n, self.used = n, used
        return out

    def find(self, hashes: np.ndarray, checks: np.ndarray) -> np.ndarray:
        """Entry number of each chunk, -1 where there is none."""
        out = np.full(len(hashes), -1, np.int64)
        at, left = (hashes >> np.uint64(64 - self.bits)).astype(np.int64), np.arange(len(hashes))
        while len(left):
            here = at[left]
            number = self.number[here]
            hit = (number >= 0) & (self.hashes[here] == hashes[left]) & (self.checks[here] == checks[left])
            out[left[hit]] = number[hit]
            left = left[(number >= 0) & ~hit]
            at[left] = (at[left] + 1) & ((1 << self.bits) - 1)
        return out

    def insert(self, hashes: np.ndarray, checks: np.ndarray, ids: np.ndarray, sizes: np.ndarray) -> np.ndarray:
        """Add distinct chunks that :meth:`find` does not know."""
        number = self.add(ids, sizes)
        at, left = (hashes >> np.uint64(64 - self.bits)).astype(np.int64), np.arange(len(hashes))
        while len(left):
            here = at[left]
            free = left[self.number[here] < 0]
            self.number[at[free]] = number[free]
            won = free[self.number[at[free]] == number[free]]  # of several that want one place, one has it
            self.hashes[at[won]], self.checks[at[won]] = hashes[won], checks[won]
            left = np.setdiff1d(left, won, assume_unique=True)
            at[left] = (at[left] + 1) & ((1 << self.bits) - 1)
        return number


class Merges:
    """Byte-pair merges of many pieces at once: in every round each piece merges its pair of least rank, leftmost first."""

    def __init__(self, vocabulary: dict[str, int], merges: list[list[str]], suffix: str) -> None:
        letters = _byte_letters()
        self.inner = np.array([vocabulary[x] for x in letters], np.int64)
        self.final = np.array([vocabulary[x + suffix] for x in letters], np.int64)
        pairs = np.array([[vocabulary[a], vocabulary[b], vocabulary[a + b]] for a, b in merges], np.int64)
        self.keys = np.r_[pairs[:, 0] << 32 | pairs[:, 1], -1]
        self.made = np.r_[pairs[:, 2], -1]
        self.none = len(merges)
        # two-level table: keys that share a place in the first go to the second, under a multiplier that parts them
        self.levels: list[tuple[np.uint64, np.ndarray]] = []
        left, factor = np.arange(len(merges)), 0x9E3779B97F4A7C15
        while len(left):
            place = np.full(1 << 20, self.none, np.int32)
            at = self._place(self.keys[left], np.uint64(factor))
            place[at] = left
            self.levels.append((np.uint64(factor), place))
            left = left[place[at] != left]
            factor = factor * 0xD6E8FEB86659FD93 % (1 << 64) | 1

    @staticmethod
    def _place(keys: np.ndarray, factor: np.uint64) -> np.ndarray:
        return ((keys.astype(np.uint64) * factor) >> np.uint64(44)).astype(np.int64)

    def ranks(self, keys: np.ndarray) -> np.ndarray:
        out = np.full(len(keys), self.none, np.int32)
        for factor, place in self.levels:
            held = place[self._place(keys, factor)]
            out = np.where(self.keys[held] == keys, held, out)
        return out

    def ids(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all pieces, piece of each id) of pieces that cover ``data`` in order, gaps apart."""
        sizes = ends - starts
        piece = np.repeat(np.arange(len(starts)), sizes)
        at = np.arange(len(piece)) - np.repeat(np.cumsum(sizes) - sizes, sizes) + starts[piece]
        ids = self.inner[data[at]]
        last = np.cumsum(sizes) - 1
        ids[last] = self.final[data[at[last]]]
        done: list[tuple[np.ndarray, np.ndarray]] = []
        while len(ids):
            rank = np.full(len(ids), self.none, np.int32)
            pair = np.flatnonzero(piece[1:] == piece[:-1])
            rank[pair] = self.ranks(ids[pair] << 32 | ids[pair + 1])
            change = np.r_[True, piece[1:] != piece[:-1]]
            least = np.minimum.reduceat(rank, np.flatnonzero(change))[np.cumsum(change) - 1]
            open_ = least < self.none
            done.append((ids[~open_], piece[~open_]))
            ids, piece, rank, least = ids[open_], piece[open_], rank[open_], least[open_]
            best = np.flatnonzero(rank == least)
            best = best[np.r_[True, piece[best][1:] != piece[best][:-1]]] if len(best) else best
            ids[best] = self.made[rank[best]]
            kept = np.ones(len(ids), bool)
            kept[best + 1] = False
            ids, piece = ids[kept], piece[kept]
        ids, piece = (np.concatenate(x) for x in zip(*done, strict=True)) if done else (ids, piece)
        order = np.argsort(piece, kind="stable")
        return ids[order], piece[order]


class Encoder:
    """Token ids of whole texts, equal to the tokenizer's own, through a table of white-space separated chunks.

    The vocabulary's rules drop white space and never join across it, so a
    text's ids are the concatenation of its chunks' ids.  Chunks of plain
    Latin characters are cut by the same pattern as the tokenizer's and merged
    by its merges; any other chunk goes to the tokenizer whole.
    """

    def __init__(self, path: str, bits: int = 20) -> None:
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.dtype = np.dtype("<u2" if self.tokenizer.get_vocab_size() <= 1 << 16 else "<u4")
        self.table = ChunkTable(self.dtype, bits)
        self.letters, self.model = _byte_letters(), self.tokenizer.model
        rules = json.loads(self.tokenizer.to_str())["model"]
        self.merges = Merges(rules["vocab"], [m if isinstance(m, list) else m.split(" ") for m in rules["merges"]], rules["end_of_word_suffix"] or "")

    def _chunk(self, chunk: str) -> np.ndarray:
        if _PLAIN.fullmatch(chunk) is None or "<|" in chunk:
            ids = self.tokenizer.encode(chunk, add_special_tokens=False).ids
        else:
            ids = []
            for piece in _PIECES.findall(unicodedata.normalize("NFC", chunk).lower()):
                ids += [t.id for t in self.model.tokenize(piece if piece.isascii() else "".join([self.letters[b] for b in piece.encode()]))]
        return np.array(ids, self.dtype)

    def _chunks(self, chunks: list[bytes], simple: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(all ids, number of ids) of chunks; the simple ones go through the merges together."""
        sizes, parts = np.zeros(len(chunks), np.int64), []
        for i in np.flatnonzero(~simple).tolist():
            parts.append(self._chunk(chunks[i].decode()))
            sizes[i] = len(parts[-1])
        own = np.flatnonzero(simple)
        data = np.frombuffer(b"\n".join([chunks[i] for i in own.tolist()]).decode().lower().encode(), np.uint8)
        kind = _KIND[data]
        begins = np.flatnonzero((kind > 0) & ((np.diff(kind, prepend=0) != 0) | (kind == 2)))
        ends = np.r_[begins[1:], len(data)] if len(begins) else begins
        ends = ends - (kind[ends - 1] == 0)
        ids, piece = self.merges.ids(data, begins, ends)
        of = own[np.cumsum(kind == 0)[begins]]
        sizes[simple] = np.bincount(of[piece], minlength=len(chunks))[simple]
        where = np.repeat(simple, sizes)
        out = np.empty(len(where), self.dtype)
        out[where] = ids
        if parts:
            out[~where] = np.concatenate(parts)
        return out, sizes

    def _numbers(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Table entry of every chunk; those that are not kept come last in the table."""
        hashes, sizes = word_hashes(data, starts, ends), ends - starts
        checks = sizes.astype(np.uint64) << np.uint64(57)
        for k in range(7):
            held = np.flatnonzero(sizes > k)
            checks[held] |= LOWER[data[ends[held] - 1 - k]].astype(np.uint64) << np.uint64(8 * k)
        out = self.table.find(hashes, checks)
        # case decides in marks of special tokens, and the check word has room for short chunks only
        special = np.flatnonzero((data[:-1] == 60) & (data[1:] == 124))
        odd = sizes > LONGEST
        if len(special):
            odd[np.searchsorted(starts, special, "right") - 1] = True
        new = np.flatnonzero((out < 0) & ~odd)
        raw = data.tobytes()

        def made(which: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            chunks = [raw[a:b] for a, b in zip(starts[which].tolist(), ends[which].tolist(), strict=True)]
            return self._chunks(chunks, simple[which])

        if len(new) or odd.any():
            bad = ~_SIMPLE[data]
            for x in _NOT_SIMPLE:
                a, b = x.encode()
                bad[:-1] |= (data[:-1] == a) & (data[1:] == b)
            count = np.r_[0, np.cumsum(bad)]
            simple = (count[ends] == count[starts]) & ~odd
        if len(new):
            _, first, own = np.unique(hashes[new], return_index=True, return_inverse=True)
            first = new[first]
            clash = checks[new] != checks[first[own]]
            odd[new[clash]] = True
            out[new] = self.table.insert(hashes[first], checks[first], *made(first))[own]
        rare = np.flatnonzero(odd)
        if len(rare):
            out[rare] = self.table.add(*made(rare))
        return out

    def encode(self, texts: list[str | None], end_id: int) -> tuple[np.ndarray, np.ndarray]:
        """(all ids, number of ids of each text); every text ends with ``end_id``."""
        table, end = self.table, np.array([end_id], self.dtype)
        held, counts = [np.zeros(0, self.dtype)], np.zeros(len(texts), np.int64)
        for rows, last, data, begins in _segments(texts):
            if table.n + len(data) // 2 > table.most:
                table.clear()
            starts, ends = runs(~SPACE[data])
            numbers = self._numbers(data, starts, ends)
            mark = table.add(end, np.ones(1, np.int64))[0]
            own = np.searchsorted(begins, starts, "right") - 1
            ahead = np.cumsum(last) - last  # end marks before each segment
            order = np.full(len(starts) + int(last.sum()), mark, np.int64)
            order[np.arange(len(starts)) + ahead[own]] = numbers
            of = np.empty(len(order), np.int64)
            of[np.arange(len(starts)) + ahead[own]] = own
            of[np.searchsorted(own, np.flatnonzero(last), "right") + np.arange(int(last.sum()))] = np.flatnonzero(last)
            sizes = table.size[order]
            ends_at = np.cumsum(sizes)
            held.append(table.ids[np.repeat(table.first[order] - (ends_at - sizes), sizes) + np.arange(int(ends_at[-1]) if len(ends_at) else 0)])
            counts += np.bincount(rows[of], sizes, len(texts)).astype(np.int64)
        return np.concatenate(held), counts


def _segments(texts: list[str | None]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(row, whether it ends its row, bytes, start) of runs of segments; long texts are cut at white space."""
    rows, last, held, size = [], [], [], 0

    def run() -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        lengths = np.fromiter(map(len, held), np.int64, len(held))
        return np.array(rows), np.array(last, np.int64), np.frombuffer(b"".join(held), np.uint8), np.cumsum(lengths) - lengths

    for row, text in enumerate(texts):
        raw, at = (text or "").encode() + b"\n", 0
        while at < len(raw):
            stop = at + SEGMENT
            while stop < len(raw) and not SPACE[raw[stop - 1]]:
                stop += 1
            part = raw[at:stop]
            rows.append(row)
            last.append(stop >= len(raw))
            held.append(part)
            size, at = size + len(part), stop
            if size >= SEGMENT:
                yield run()
                rows, last, held, size = [], [], [], 0
    if held:
        yield run()


@lru_cache(maxsize=2)
def _encoder(path: str) -> Encoder:
    return Encoder(path)


def encoder(path: str) -> Encoder:
    WORKER_CACHES["tokens"] = _encoder.cache_clear
    return _encoder(path)


def floor_share(part: np.ndarray, at: np.ndarray, share: int) -> np.ndarray:
    """floor(part * at / share) for 0 <= part <= share and results below 2**52, exact although the product may not fit 64 bits.

    The quotient is guessed in floating point; the remainder is small, so its low 64 bits say how far the guess is off.
    """
    part, at = np.broadcast_arrays(np.asarray(part, np.int64), np.asarray(at, np.int64))
    guess = np.floor(part.astype(float) * at / share).astype(np.int64)
    with np.errstate(over="ignore"):
        rest = part * at - guess * share
        while (low := rest < 0).any():
            guess, rest = guess - low, rest + low * share
        while (high := rest >= share).any():
            guess, rest = guess + high, rest - high * share
    return guess


class Stream:
    """A stream of ``sizes.sum()`` tokens in windows of ``length`` that serve every queue in proportion to its size.

    The queues lie side by side on [0, total]; by token ``at`` of the stream,
    the first ones up to an edge have been served floor(edge * at / total)
    tokens, so windows are full and a queue's service, a difference of two
    such floors, is within two tokens of its share.  It never falls from one
    window to the next for queues with at least a token a window, nor for the first queue.
    Thinner queues are pooled in the first place; the pool is a
    stream of its own, with windows ``quantum`` times as long, so a thin queue
    is served up to about ``quantum`` tokens at a time and then waits.
    """

    def __init__(self, sizes: np.ndarray, length: int, quantum: int) -> None:
        self.queues, self.total, self.length = sizes, int(sizes.sum()), length
        thin = sizes < -(-self.total // length)
        pool = int(sizes[thin].sum())
        self.sizes = np.r_[pool, sizes[~thin]]
        self.edges = np.r_[0, np.cumsum(self.sizes)]
        self.place = np.where(thin, np.cumsum(thin) - 1, np.cumsum(~thin))
        self.thin = thin
        self.pool = Stream(sizes[thin], min(pool, quantum * max(1, pool * length // self.total)), quantum) if pool else None

    def _served(self, place: np.ndarray, at: np.ndarray) -> np.ndarray:
        return self._ahead(place + 1, at) - self._ahead(place, at)

    def _ahead(self, place: np.ndarray, at: np.ndarray) -> np.ndarray:
        return floor_share(self.edges[place], np.minimum(at, self.total), self.total)

    def _window(self, place: np.ndarray, token: np.ndarray) -> np.ndarray:
        """The window that holds each queue's token."""
        # served tokens are within one of the share, which bounds the search
        pace = self.sizes[place] * (self.length / self.total)
        final = (self.total - 1) // self.length
        low = np.clip(np.floor((token - 1) / pace).astype(np.int64) - 2, 0, final)
        high = np.clip(np.floor((token + 2) / pace).astype(np.int64) + 2, 0, final)
        while (open_ := low < high).any():
            mid = (low + high + 1) // 2
            fits = self._served(place, mid * self.length) <= token
            low, high = np.where(open_ & fits, mid, low), np.where(open_ & ~fits, mid - 1, high)
        return low

    def _cut(self, place: np.ndarray, low: np.ndarray, high: np.ndarray, by_window: bool) -> tuple[np.ndarray, ...]:
        """(owner, first, last, window, offset); a queue with a token or more a window is listed by windows, a thinner one by its tokens."""
        if by_window:
            first = self._window(place, low)
            count = self._window(place, high - 1) - first + 1
        else:
            first, count = low, high - low
        owner = np.repeat(np.arange(len(place)), count)
        ramp = np.arange(len(owner)) - np.repeat(np.cumsum(count) - count, count) + first[owner]
        w = ramp if by_window else self._window(place[owner], ramp)
        if not by_window:
            fresh = np.r_[True, (owner[1:] != owner[:-1]) | (w[1:] != w[:-1])]
            owner, w = owner[fresh], w[fresh]
        q = place[owner]
        begin, end = w * self.length, (w + 1) * self.length
        ahead, before = self._ahead(q, begin), self._ahead(q, end)
        start, stop = self._ahead(q + 1, begin) - ahead, self._ahead(q + 1, end) - before
        a, b = np.maximum(low[owner], start), np.minimum(high[owner], stop)
        some = a < b
        return tuple(x[some] for x in (owner, a, b, w, before - ahead + a - start))

    def pieces(self, queue: np.ndarray, low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, ...]:
        """(owner, first, last, window, offset) of the pieces of each queue's tokens low..high."""
        thin = self.thin[queue]
        out = []
        if (own := np.flatnonzero(~thin)).size:
            owner, *rest = self._cut(self.place[queue[own]], low[own], high[own], True)
            out.append((own[owner], *rest))
        if (own := np.flatnonzero(thin)).size:
            owner, first, last, window, offset = self.pool.pieces(self.place[queue[own]], low[own], high[own])
            at = window * self.pool.length + offset
            by_window = int(self.sizes[0]) >= -(-self.total // self.length)
            of, a, b, window, offset = self._cut(np.zeros(len(at), np.int64), at, at + last - first, by_window)
            shift = (first - at)[of]
            out.append((own[owner[of]], a + shift, b + shift, window, offset))
        return tuple(np.concatenate(x) for x in zip(*out, strict=True))


class Schedule:
    """Which window and offset a queue's tokens get: phases of constant shares, in exact integer arithmetic.

    ``targets`` are the weights of the first queues; phases hold numbers of these queues only until they have run dry.
    """

    def __init__(self, totals: list[int], targets: list[float] | None, length: int, quantum: int = 64) -> None:
        self.length = length
        totals = np.array(totals, np.int64)
        #: (first window, tokens of each queue served before, stream)
        self.phases: list[tuple[int, np.ndarray, Stream]] = []
        start, left, served = 0, totals.copy(), np.zeros(len(totals), np.int64)
        weights = [max(0, round(t * 1_000_000)) for t in targets or []]
        k = len(weights)
        while left.any():
            wanted = [i for i in range(k) if left[i] and weights[i]]
            sizes = left.copy()
            if wanted:
                share = sum(weights[i] for i in wanted)
                # whole windows until the first queue runs dry; if there is none, one window in which it does
                span = min(int(left[i]) * share // weights[i] for i in wanted) // length * length
                sizes = np.zeros(k, np.int64) if span else self._last_window(left, weights, wanted)
                if span:
                    sizes[wanted] = np.diff(_floors([weights[i] for i in wanted], span))
                elif not sizes[k:].any():
                    sizes = sizes[:k]
            n = len(sizes)
            self.phases.append((start // length, served[:n].copy(), Stream(sizes, length, quantum)))
            left[:n] -= sizes
            served[:n] += sizes
            start += int(sizes.sum())
        self.total, self.served = start, served

    def _last_window(self, left: np.ndarray, weights: list[int], wanted: list[int]) -> np.ndarray:
        """One window in which queues about to run dry give all they have and the others fill it by weight, then by size."""
        take, room, live = np.zeros(len(left), np.int64), self.length, set(wanted)
        while room and live:
            share = sum(weights[i] for i in live)
            dry = [i for i in sorted(live) if int(left[i] - take[i]) * share <= weights[i] * room]
            if not dry:
                take[sorted(live)] += np.diff(_floors([weights[i] for i in sorted(live)], room))
                return take
            for i in dry:
                given = min(room, int(left[i] - take[i]))
                room -= given
                take[i] += given
                live.discard(i)
        rest = left - take
        if room and rest.any():
            size = int(rest.sum())
            take += np.diff(floor_share(np.r_[0, np.cumsum(rest)], np.int64(min(room, size)), size))
        return take

    def cuts(self, queue: np.ndarray, start: np.ndarray, stop: np.ndarray) -> tuple[np.ndarray, ...]:
        """(owner, first, last, window, offset) of the pieces of each queue's tokens start..stop; first is a queue position."""
        out = []
        for window, before, stream in self.phases:
            own = np.flatnonzero(queue < len(before))
            q = queue[own]
            base = before[q]
            low, high = np.maximum(start[own] - base, 0), np.minimum(stop[own] - base, stream.queues[q])
            some = np.flatnonzero(low < high)
            if len(some):
                owner, first, last, w, offset = stream.pieces(q[some], low[some], high[some])
                own, shift = own[some][owner], base[some][owner]
                out.append((own, first + shift, last + shift, w + window, offset))
        return tuple(np.concatenate(x) for x in zip(*out, strict=True)) if out else tuple(np.zeros(0, np.int64) for _ in range(5))


def _floors(weights: list[int], at: int) -> np.ndarray:
    """floor(at * cumulated weight / sum of weights), from 0 to ``at``."""
    run, out = 0, [0]
    for w in weights:
        run += w
        out.append(run * at)
    return np.array([x // max(run, 1) for x in out], np.int64)


def tokenise(documents: DataFrame, tokenizer: str, end_id: int) -> DataFrame:
    """(doc_id, queue, part, before, tokens, ids): ``before`` counts the tokens of the same queue earlier in the same partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        release_worker_memory("tokens")
        part, code = TaskContext.get().partitionId(), encoder(tokenizer)
        before: dict[str, int] = {}
        for batch in batches:
            if not batch.num_rows:
                continue
            ids, counts = code.encode(batch.column("text").to_pylist(), end_id)
            starts = []
            for q, n in zip(batch.column("queue").to_pylist(), counts.tolist(), strict=True):
                starts.append(before.get(q, 0))
                before[q] = starts[-1] + n
            edges = (np.r_[0, np.cumsum(counts)] * code.dtype.itemsize).astype(np.int32)
            binary = pa.Array.from_buffers(pa.binary(), batch.num_rows, [None, pa.py_buffer(edges), pa.py_buffer(ids)])
            yield pa.record_batch(
                [batch.column("doc_id"), batch.column("queue"), pa.array(np.full(batch.num_rows, part, np.int32)), pa.array(starts, pa.int64()), pa.array(counts), binary],
                ["doc_id", "queue", "part", "before", "tokens", "ids"],
            )

    rows = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.concat(F.lit("s"), F.col("source").cast("string")), F.lit("-")).alias("queue"), "text")
    bound_batches(rows.sparkSession)
    return rows.mapInArrow(run, "doc_id long, queue string, part int, before long, tokens long, ids binary")


def pack(documents: DataFrame, tokenizer: str, end_id: int = 2, length: int = 4096, targets: dict[str | None, float] | None = None, quantum: int = 64, broadcast_rows: int = 1 << 20) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, queue.

    ``targets`` maps sources to weights; without it shares are measured.
    """
    named = {"-" if s is None else f"s{s}": w for s, w in (targets or {}).items()}
    spark = documents.sparkSession
    tokens = materialise(tokenise(documents, tokenizer, end_id), "tokens")
    rows = tokens.count()
    parts = materialise(tokens.groupBy("queue", "part").agg(F.sum("tokens").alias("n")), "queue-parts", rows)
    totals = {r.queue: r.n for r in parts.groupBy("queue").agg(F.sum("n").alias("n")).collect()}  # one row a source
    queues = sorted(totals, key=lambda q: (q not in named, q))
    plan = Schedule([totals[q] for q in queues], [float(named[q]) for q in queues if q in named] if targets else None, length, quantum)
    shipped = spark.sparkContext.broadcast(plan)
    dtype = encoder(tokenizer).dtype
    numbers = spark.createDataFrame(pa.table({"queue": pa.array(queues, pa.string()), "number": pa.array(np.arange(len(queues)), pa.int64())}))
    # one row per (queue, partition): prefix sums over partitions, not over documents
    ahead = F.sum("n").over(Window.partitionBy("queue").orderBy("part")) - F.col("n")
    bases = materialise(parts.select("queue", "part", ahead.alias("base")).join(numbers, "queue"), "queue-bases", rows)
    side = F.broadcast(bases) if bases.count() <= broadcast_rows else bases
    placed = tokens.join(side, ["queue", "part"]).select("doc_id", "queue", "number", (F.col("base") + F.col("before")).alias("at"), "tokens", "ids")

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        queue, at, n = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("number", "at", "tokens"))
        owner, first, last, window, offset = shipped.value.cuts(queue, at, at + n)
        order = np.lexsort((first, owner))
        owner, first, last, window, offset = (x[order] for x in (owner, first, last, window, offset))
        wide = memoryview(np.frombuffer(b"".join(batch.column("ids").to_pylist()), dtype).astype("<u4")).cast("B")
        begin = (np.cumsum(n) - n)[owner] - at[owner]
        sums = [zlib.crc32(wide[a:b]) for a, b in zip((4 * (begin + first)).tolist(), (4 * (begin + last)).tolist(), strict=True)]
        take = pa.array(owner)
        columns = [batch.column("doc_id").take(take), pa.array(first - at[owner]), pa.array(last - first), pa.array(sums, pa.int64()), pa.array(n[owner]), pa.array(window), pa.array(offset), batch.column("queue").take(take)]
        return pa.record_batch(columns, ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "queue"])

    return map_arrow(placed, kernel, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, queue string")

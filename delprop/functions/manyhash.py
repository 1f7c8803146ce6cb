"""The portable hash of :mod:`hashing` over NumPy vectors: many ids or many salts in a batch, without a string a value."""

from __future__ import annotations

import numpy as np

from delprop.functions.hashing import SCALE, uniform_of

_SHIFTS = (7, 12, 17, 22, 5, 9, 14, 20, 4, 11, 16, 23, 6, 10, 15, 21)
_SINES = [int(abs(np.sin(i + 1.0)) * 4294967296.0) & 0xFFFFFFFF for i in range(64)]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
#: Values hashed at once, so that the working vectors stay in the cache.
_STEP = 8192


def _place(i: int) -> int:
    return (i, (5 * i + 1) % 16, (3 * i + 5) % 16, 7 * i % 16)[i // 16]


def _first_word(words: list[np.ndarray | int], n: int) -> np.ndarray:
    """The first four bytes of the md5 of one-block messages; ``words`` are sixteen vectors or constants.

    The first word of the digest is the value made in the third round before the last.
    """
    a, b, c, d = (np.full(n, v, np.uint32) for v in _START)
    f, t = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(61):
        kind, word = i // 16, words[_place(i)]
        if kind == 0:
            np.bitwise_xor(c, d, out=f)
            np.bitwise_and(f, b, out=f)
            np.bitwise_xor(f, d, out=f)
        elif kind == 1:
            np.bitwise_xor(b, c, out=f)
            np.bitwise_and(f, d, out=f)
            np.bitwise_xor(f, c, out=f)
        elif kind == 2:
            np.bitwise_xor(b, c, out=f)
            np.bitwise_xor(f, d, out=f)
        else:
            np.bitwise_not(d, out=f)
            np.bitwise_or(f, b, out=f)
            np.bitwise_xor(f, c, out=f)
        np.add(f, a, out=f)
        if isinstance(word, int):
            np.add(f, np.uint32((_SINES[i] + word) & 0xFFFFFFFF), out=f)
        else:
            np.add(f, np.uint32(_SINES[i]), out=f)
            np.add(f, word, out=f)
        s = _SHIFTS[kind * 4 + i % 4]
        np.left_shift(f, np.uint32(s), out=t)
        np.right_shift(f, np.uint32(32 - s), out=f)
        np.bitwise_or(f, t, out=f)
        np.add(f, b, out=a)
        a, b, c, d = d, a, b, c
    return (b + np.uint32(_START[0])).byteswap()


def _digits(ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Decimal digits (n x 20, right-aligned) and how many each id has."""
    out, rest = np.empty((len(ids), 20), np.uint8), ids.astype(np.uint64)
    counts = np.ones(len(ids), np.int64)
    for k in range(19, -1, -1):
        quotient = rest // np.uint64(10)
        out[:, k] = (rest - quotient * np.uint64(10)).astype(np.uint8)
        rest = quotient
        counts += rest != 0
    return out + 48, counts


def uniforms(ids: np.ndarray, salts: list[str]) -> np.ndarray:
    """(ids x salts): :func:`hashing.uniform` of every pair."""
    ids = np.asarray(ids, np.int64)
    out = np.empty((len(ids), len(salts)))
    if (ids < 0).any() or max((len(s.encode()) for s in salts), default=0) > 34:  # beyond one block or with a sign
        for i, key in enumerate(ids.tolist()):
            out[i] = [uniform_of(key, s) for s in salts]
        return out
    digits, counts = _digits(ids)
    sizes, group = np.unique(counts, return_inverse=True)
    text = np.zeros((len(ids), 20), np.uint8)
    for g, count in enumerate(sizes):
        own = np.flatnonzero(group == g) if len(sizes) > 1 else slice(None)
        text[own, :count] = digits[own, 20 - count :]
    heads, tails = text.view("<u4"), np.array([[_tail(int(count), s) for s in salts] for count in sizes]).reshape(len(sizes), len(salts), 16)
    full = -(-int(counts.max(initial=1)) // 4)
    for a in range(0, len(ids), _STEP):
        some, own = heads[a : a + _STEP], group[a : a + _STEP]
        width = max(1, _STEP // len(some))  # few ids: several salts at once
        for k in range(0, len(salts), width):
            few = tails[:, k : k + width]
            found = _first_word(_words(some, few, own, full), len(some) * few.shape[1])
            out[a : a + _STEP, k : k + width] = found.reshape(len(some), -1) / SCALE
    return out


def _tail(count: int, salt: str) -> np.ndarray:
    """The words of a message without its first ``count`` characters."""
    tail, message = b":" + salt.encode(), bytearray(64)
    message[count : count + len(tail)] = tail
    message[count + len(tail)] = 0x80
    message[56:60] = ((count + len(tail)) * 8).to_bytes(4, "little")
    return np.frombuffer(bytes(message), "<u4")


def _words(heads: np.ndarray, tails: np.ndarray, group: np.ndarray, full: int) -> list[np.ndarray | int]:
    """The sixteen words of every (id, salt), ids outermost: constants where all are equal; ``group`` is an id's number of characters in ``tails``."""
    words: list[np.ndarray | int] = []
    for w in range(16):
        own = tails[:, :, w]
        if w >= full and (own == own[0, 0]).all():
            words.append(int(own[0, 0]))
            continue
        own = own[group] if len(own) > 1 else np.broadcast_to(own[0], (len(heads), own.shape[1]))
        words.append((heads[:, w, None] | own).ravel() if w < full else own.ravel())
    return words


def uniforms_of(ids: np.ndarray, salt: str) -> np.ndarray:
    return uniforms(ids, [salt])[:, 0]

"""Sums over the sliding windows of series without a row a window."""

from __future__ import annotations

import numpy as np

#: Lags worked off at once.
_LAGS = 8


def fast_length(least: int) -> int:
    """The least product of twos, threes and fives that is not below ``least``."""
    found = 1 << max(0, least - 1).bit_length()
    five = 1
    while five < found:
        both = five
        while both < found:
            found = min(found, both << max(0, -(-least // both) - 1).bit_length())
            both *= 3
        five *= 5
    return found


def sliding_grams(series: list[np.ndarray], weights: list[np.ndarray], m: int) -> np.ndarray:
    """(p x m x m): sums of ``weights[k][t, p]`` times the outer product of ``series[k][t : t + m]`` with itself, over all k and t.

    At lag d, the entries (a, a + d) are the weights' correlation with the
    products of values d apart; all series meet between the transforms.
    """
    n = fast_length(max(map(len, series)))
    vals, held = np.zeros((len(series), n)), np.zeros((len(series), weights[0].shape[1], n))
    for k, (v, w) in enumerate(zip(series, weights, strict=True)):
        vals[k, : len(v)] = v
        held[k, :, : len(w)] = w.T
    spectra = np.ascontiguousarray(np.fft.rfft(held).conj().transpose(2, 0, 1))
    out = np.empty((held.shape[1], m, m))
    for first in range(0, m, _LAGS):
        lags = range(first, min(m, first + _LAGS))
        apart = np.zeros((len(lags), len(series), n))
        for k, lag in enumerate(lags):
            np.multiply(vals[:, : n - lag], vals[:, lag:], out=apart[k, :, : n - lag])
        met = np.ascontiguousarray(np.fft.rfft(apart).transpose(2, 0, 1)) @ spectra
        found = np.fft.irfft(met.transpose(1, 2, 0), n)
        for k, lag in enumerate(lags):
            a = np.arange(m - lag)
            out[:, a, a + lag] = out[:, a + lag, a] = found[k, :, : m - lag]
    return out

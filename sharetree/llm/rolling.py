"""Vectorised hashing of bytes, words and their windows, the same in every process."""

from __future__ import annotations

import numpy as np

_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)
_powers = np.ones(1, np.uint64)
_inverses = np.ones(1, np.uint64)
#: Bytes that part words: space and 9 to 13.
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True


def _tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers 0 to n of the base and of its inverse, modulo 2**64."""
    global _powers, _inverses
    if len(_powers) <= n:
        size = max(n + 1, 2 * len(_powers), 1 << 16)
        for base, name in ((_BASE, "_powers"), (_INVERSE, "_inverses")):
            out = np.full(size, base, np.uint64)
            out[0] = 1
            globals()[name] = np.multiply.accumulate(out)
    return _powers, _inverses


def mix(h: np.ndarray) -> np.ndarray:
    """Spreads a 64-bit number over all its bits (one to one)."""
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def spans_hash(data: np.ndarray, starts: np.ndarray, stops: np.ndarray) -> np.ndarray:
    """Hash of data[start:stop] for each pair; equal stretches hash alike wherever they stand."""
    powers, inverses = _tables(len(data))
    sums = np.zeros(len(data) + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * powers[: len(data)], out=sums[1:])
    return mix((sums[stops] - sums[starts]) * inverses[starts])


def windows_hash(data: np.ndarray, width: int) -> np.ndarray:
    """Hash of every window of ``width`` units."""
    n = len(data) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    powers, inverses = _tables(len(data))
    sums = np.zeros(len(data) + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * powers[: len(data)], out=sums[1:])
    return mix((sums[width:] - sums[:n]) * inverses[:n])


def word_spans(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Start and stop of each word of a byte array."""
    space = np.ones(len(data) + 2, bool)
    space[1:-1] = _SPACE[data]
    edges = np.flatnonzero(space[1:] != space[:-1])
    return edges[0::2], edges[1::2]


def word_hashes(data: np.ndarray) -> np.ndarray:
    starts, stops = word_spans(data)
    return spans_hash(data, starts, stops) if len(starts) else np.zeros(0, np.uint64)

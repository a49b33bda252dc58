"""Words, word hashes and word shingles of many texts at once, in numpy.

A word is a maximal run of bytes other than the six ASCII white-space bytes. Prefix sums
of a polynomial over the bytes, modulo 2**64, give the hash of any run in constant time,
so a slice of texts needs no Python loop over words.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

_U = np.uint64
_BASE = 0x9E3779B97F4A7C15 | 1
_BASE_INV = pow(_BASE, -1, 1 << 64)
_powers = {"up": np.ones(1, _U), "down": np.ones(1, _U)}

IS_WORD = np.ones(256, bool)
IS_WORD[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = False
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads every input bit over all 64 output bits."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
        return x ^ (x >> _U(31))


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse, ``n`` of each; kept for the worker's life."""
    if len(_powers["up"]) < n:
        n = max(n, 1 << 19)
        with np.errstate(over="ignore"):
            for key, base in (("up", _BASE), ("down", _BASE_INV)):
                steps = np.full(n, base, _U)
                steps[0] = 1
                _powers[key] = np.cumprod(steps, dtype=_U)
    return _powers["up"], _powers["down"]


def word_bounds(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end bytes of the words of all texts, and for each text where its words begin."""
    n = len(data)
    if n == 0:
        none = np.zeros(0, np.int64)
        return none, none, np.zeros(len(offsets), np.int64)
    inside = IS_WORD[data]
    before = np.empty(n, bool)
    before[0], before[1:] = False, inside[:-1]
    filled = offsets[:-1] < offsets[1:]
    before[offsets[:-1][filled]] = False
    after = np.empty(n, bool)
    after[-1], after[:-1] = False, inside[1:]
    after[offsets[1:][filled] - 1] = False
    starts = np.flatnonzero(inside & ~before)
    ends = np.flatnonzero(inside & ~after) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def run_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each byte run ``[start, end)``."""
    up, down = powers(len(data) + 1)
    with np.errstate(over="ignore"):
        sums = np.empty(len(data) + 1, _U)
        sums[0] = 0
        np.cumsum((data.astype(_U) + _U(1)) * up[: len(data)], out=sums[1:])
        return mix((sums[ends] - sums[starts]) * down[starts])


def window_hashes(words: np.ndarray, n: int) -> np.ndarray:
    """Hashes of every ``n`` words in a row, in order; empty if there are fewer."""
    if len(words) < n:
        return np.zeros(0, _U)
    with np.errstate(over="ignore"):
        total = np.zeros(len(words) - n + 1, _U)
        for j in range(n):
            total = total * _U(0xD6E8FEB86659FD93) + words[j : len(words) - n + 1 + j]
    return mix(total)


def word_hash_lists(data: np.ndarray, offsets: np.ndarray, lower: bool = True) -> Iterator[np.ndarray]:
    """Word hashes of each text of a slice."""
    if lower:
        data = LOWER[data]
    starts, ends, first = word_bounds(data, offsets)
    hashes = run_hashes(data, starts, ends)
    for i in range(len(offsets) - 1):
        yield hashes[first[i] : first[i + 1]]


def shingle_counts(words: np.ndarray, n: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingles of ``n`` words with their counts.

    A text of one to ``n - 1`` words is one shingle; a text without words has none.
    """
    found = window_hashes(words, min(n, len(words))) if len(words) else words
    return np.unique(found, return_counts=True)

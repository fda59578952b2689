"""Vectorised hashing of words and word shingles (numpy, one text at a time)."""

from __future__ import annotations

import numpy as np

_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[0x41:0x5B] += 0x20
_BASE, _MIX1, _MIX2, _STEP = (np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB, 0xD6E8FEB86659FD93))
_INVERSE = np.uint64(pow(int(_BASE), -1, 1 << 64))
_held = {False: np.ones(1, np.uint64), True: np.ones(1, np.uint64)}


def powers(n: int, inverse: bool = False) -> np.ndarray:
    """At least n powers of the base, or of its inverse, modulo 2^64."""
    if len(_held[inverse]) < n:
        size = max(n, 2 * len(_held[inverse]))
        with np.errstate(over="ignore"):
            _held[inverse] = np.cumprod(np.concatenate([np.ones(1, np.uint64), np.full(size, _INVERSE if inverse else _BASE)]), dtype=np.uint64)
    return _held[inverse]


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit moves every output bit."""
    x = (x ^ (x >> np.uint64(30))) * _MIX1
    x = (x ^ (x >> np.uint64(27))) * _MIX2
    return x ^ (x >> np.uint64(31))


def word_spans(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Byte offsets where words start and end (maximal runs without white space)."""
    solid = np.empty(len(raw) + 2, dtype=np.int8)
    solid[0] = solid[-1] = 0
    np.logical_not(_SPACE[raw], out=solid[1:-1], casting="unsafe")
    edge = np.diff(solid)
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)


def word_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray, fold: bool) -> np.ndarray:
    """A 64-bit hash of each word; ``fold`` lower-cases A-Z."""
    if not len(starts):
        return np.zeros(0, dtype=np.uint64)
    sizes = ends - starts
    at = np.repeat(starts - np.concatenate([[0], np.cumsum(sizes)[:-1]]), sizes) + np.arange(sizes.sum())
    letters = (_FOLD[raw[at]] if fold else raw[at]).astype(np.uint64) + np.uint64(1)
    local = at - np.repeat(starts, sizes)
    sums = np.add.reduceat(letters * powers(int(sizes.max()) + 1)[local], np.concatenate([[0], np.cumsum(sizes)[:-1]]))
    return mix(sums + sizes.astype(np.uint64) * _STEP)


def run_hashes(words: np.ndarray, k: int) -> np.ndarray:
    """Hash of every run of k consecutive words."""
    n = len(words) - k + 1
    h = mix(words[:n] + np.uint64(k))
    for i in range(1, k):
        h = mix(h * _STEP + words[i : n + i])
    return h


def encode(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-8", "surrogatepass"), dtype=np.uint8)


def shingle_set(text: str, k: int = 5) -> np.ndarray:
    """Sorted distinct shingle hashes; a text of fewer than k words has its whole sequence as one."""
    raw = encode(text)
    words = word_hashes(raw, *word_spans(raw), fold=True)
    if not len(words):
        return words
    return np.unique(run_hashes(words, min(k, len(words))))

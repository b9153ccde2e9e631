"""Hashed affixes and character n-grams of distinct words, without loops over letters."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

from pathalgebra.llm.shingles import mix
from pathalgebra.llm.words import byte_table

_MARK = 2


def letter_table() -> np.ndarray:
    """Folds A-Z and makes every other ASCII character but a-z a blank."""
    table = byte_table(lower=True)
    letters = np.zeros(256, bool)
    letters[97:123] = True
    letters[65:91] = True
    letters[128:] = True
    table[~letters] = 32
    return table


def letter_matrix(words: list[str]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(which words, code points between marks, lengths with marks), by length."""
    sizes = np.fromiter(map(len, words), np.int64, len(words))
    low = -1
    for high in (6, 12, 24, 64, int(sizes.max()) if len(sizes) else 0):
        which = np.flatnonzero((sizes > low) & (sizes <= high))
        low = max(low, high)
        step = max(1, 400_000 // (high + 2))
        for at in range(0, len(which), step):
            part = which[at : at + step]
            width = int(sizes[part].max())
            points = np.array([words[i] for i in part], dtype=f"U{max(1, width)}").view(np.uint32).reshape(len(part), -1)
            out = np.zeros((len(part), width + 2), np.uint64)
            out[:, 0] = _MARK
            out[:, 1 : width + 1] = points[:, :width]
            lengths = sizes[part] + 2
            out[np.arange(len(part)), lengths - 1] = _MARK
            yield part, out, lengths


def ngrams(points: np.ndarray, lengths: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """64-bit numbers of all n-grams and which of them exist."""
    count = points.shape[1] - n + 1
    if count <= 0:
        return np.zeros((len(points), 0), np.uint64), np.zeros((len(points), 0), bool)
    value = np.full((len(points), count), n, np.uint64)
    for k in range(n):
        value = value * np.uint64(1_000_003) + points[:, k : k + count]
    return mix(value), np.arange(count)[None, :] <= (lengths - n)[:, None]


def affixes(points: np.ndarray, lengths: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """64-bit numbers of the first n and the last n letters, marks included."""
    row = np.arange(len(points))
    first = np.full(len(points), 100 + n, np.uint64)
    last = np.full(len(points), 200 + n, np.uint64)
    for k in range(n):
        first = first * np.uint64(1_000_003) + points[:, min(k, points.shape[1] - 1)]
        last = last * np.uint64(1_000_003) + points[row, np.maximum(lengths - n + k, 0)]
    return mix(first), mix(last)


def whole(points: np.ndarray) -> np.ndarray:
    value = np.full(len(points), 7, np.uint64)
    factor = np.uint64(1_000_003)
    for k in range(points.shape[1]):
        here = points[:, k]
        value = np.where(here > 0, value * factor + here, value)
    return mix(value)

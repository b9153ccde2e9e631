"""Cutting whole texts into words in bulk, on Arrow buffers.

ASCII bytes never occur inside a longer UTF-8 character, so a table over bytes
may fold case or turn separators into blanks before Arrow splits at blanks.
Words come back as codes into the distinct words of the block: Python then sees
every distinct word once, however often it occurs.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: White space of the word pattern, bytes 9 to 13 and 32.
SPACES = (9, 10, 11, 12, 13, 32)


def byte_table(lower: bool = False, blanks: tuple[int, ...] = SPACES) -> np.ndarray:
    table = np.arange(256, dtype=np.uint8)
    table[list(blanks)] = 32
    if lower:
        table[65:91] += 32
    return table


def mapped(texts: pa.Array, table: np.ndarray) -> pa.Array:
    """The texts with every byte looked up in ``table``; null becomes empty."""
    texts = pc.fill_null(texts.cast(pa.string()), "")
    if texts.offset or not len(texts):
        texts = pa.concat_arrays([texts, pa.array([""], pa.string())])[: len(texts)]
    _, offsets, data = texts.buffers()
    if data is None:
        return texts
    new = pa.py_buffer(table[np.frombuffer(data, np.uint8)])
    return pa.StringArray.from_buffers(len(texts), offsets, new)


def blocks(texts: pa.Array, most_bytes: int = 8_000_000) -> Iterator[tuple[int, pa.Array]]:
    """Runs of consecutive texts of about so many bytes; a longer text is alone."""
    sizes = pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False)
    total = np.cumsum(sizes)
    at = 0
    while at < len(texts):
        before = total[at - 1] if at else 0
        stop = max(at + 1, int(np.searchsorted(total, before + most_bytes, "right")))
        yield at, texts.slice(at, stop - at)
        at = stop


def split_words(texts: pa.Array, table: np.ndarray, keep_empty: bool = False) -> tuple[np.ndarray, np.ndarray, list[str]]:
    """(ends, codes, distinct): text k has ``distinct[codes[ends[k-1]:ends[k]]]``."""
    parts = pc.split_pattern(mapped(texts, table), " ")
    offsets = parts.offsets.to_numpy().astype(np.int64)
    encoded = parts.flatten().dictionary_encode()
    codes = encoded.indices.to_numpy(zero_copy_only=False)
    distinct = encoded.dictionary.to_numpy(zero_copy_only=False).tolist()
    ends = offsets[1:] - offsets[0]
    if keep_empty or "" not in (d := {w: k for k, w in enumerate(distinct) if not w}):
        return ends, codes, distinct
    real = codes != d[""]
    after = np.concatenate([[0], np.cumsum(real)])
    return after[ends], codes[real], distinct


def ragged(first: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Indices of all elements of runs that start at ``first``."""
    after = np.cumsum(sizes)
    if not len(after):
        return np.empty(0, np.int64)
    return np.repeat(first - after + sizes, sizes) + np.arange(int(after[-1]))

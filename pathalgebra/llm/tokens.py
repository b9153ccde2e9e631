"""Token ids of whole texts by a public tokenizer, with words encoded once.

The tokenizer never joins anything over a blank or a line feed: it makes white
space a border before it looks up pieces.  So a text's ids are those of its
chunks between blanks, and chunks that were seen before come from a table.
Chunks of plain Latin letters are cut into pieces here and looked up in the
tokenizer's merge model; any other chunk goes through the whole tokenizer.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

from pathalgebra.llm.memory import caches
from pathalgebra.llm.words import blocks, byte_table, ragged, split_words

#: Fixed values of the tokenizer's own cutting, for Latin-1 letters in lower case.
_PIECE = re.compile("'s|'t|'re|'ve|'m|'ll|'d|[a-zß-öø-ÿ]+|[0-9]|[^\\sa-z0-9ß-öø-ÿ]+")
#: Printable ASCII but "<", which may open a special token, and Latin-1 letters.
_PLAIN = re.compile("[!-;=-~À-ÖØ-öø-ÿ]+")


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))


def _byte_letters() -> dict[int, str]:
    """The usual printable stand-ins of byte-level vocabularies."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    out = {b: chr(b) for b in shown}
    for b in range(256):
        if b not in out:
            out[b] = chr(256 + len(out) - len(shown))
    return out


class WordEncoder:
    """Encodes texts in bulk; chunks between blanks are encoded once.

    ``cache_limit``: so many distinct chunks are held at most; then the table
    starts anew, which costs time and never changes a result.
    """

    def __init__(self, path: str, end_id: int | None = 1, cache_limit: int = 250_000):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.end_id = end_id
        self.cache_limit = cache_limit
        self._table = byte_table(blanks=(10, 32))
        self._letters = _byte_letters()
        # The shortcut holds for vocabularies that lower their text and mark ends of words.
        self._short = bool(self.tokenizer.normalizer) and getattr(self.tokenizer.model, "end_of_word_suffix", None) == "</w>"
        self._reset()

    def _reset(self) -> None:
        self.index: dict[str, int] = {}
        self.pieces: dict[str, list[int]] = {}
        self.flat = np.empty(1 << 16, np.uint32)
        self.first = np.empty(1 << 14, np.int64)
        self.count = np.empty(1 << 14, np.int64)
        self.used = 0

    def _piece(self, piece: str) -> list[int]:
        got = self.pieces.get(piece)
        if got is None:
            shown = piece if piece.isascii() else "".join(self._letters[b] for b in piece.encode())
            got = self.pieces[piece] = [t.id for t in self.tokenizer.model.tokenize(shown)]
        return got

    def _ids(self, chunk: str) -> list[int]:
        if self._short and _PLAIN.fullmatch(chunk):
            out: list[int] = []
            for piece in _PIECE.findall(chunk.lower()):
                out += self._piece(piece)
            return out
        return self.tokenizer.encode(chunk, add_special_tokens=False).ids if chunk else []

    def _learn(self, chunks: list[str]) -> None:
        ids = [self._ids(x) for x in chunks]
        sizes = np.fromiter(map(len, ids), np.int64, len(ids))
        total, known = int(sizes.sum()), len(self.index)
        while self.used + total > len(self.flat):
            self.flat = np.concatenate([self.flat, np.empty_like(self.flat)])
        while known + len(chunks) > len(self.first):
            self.first = np.concatenate([self.first, np.empty_like(self.first)])
            self.count = np.concatenate([self.count, np.empty_like(self.count)])
        self.flat[self.used : self.used + total] = np.fromiter((i for x in ids for i in x), np.uint32, total)
        self.count[known : known + len(chunks)] = sizes
        self.first[known : known + len(chunks)] = self.used + np.cumsum(sizes) - sizes
        self.index.update(zip(chunks, range(known, known + len(chunks)), strict=True))
        self.used += total
        if len(self.pieces) > self.cache_limit // 2:
            self.pieces = {}

    def _block(self, texts: pa.Array) -> list[np.ndarray]:
        ends, codes, distinct = split_words(texts, self._table, keep_empty=True)
        if len(self.index) > self.cache_limit:
            self._reset()
        missing = [w for w in distinct if w not in self.index]
        if missing:
            self._learn(missing)
        place = np.fromiter(map(self.index.__getitem__, distinct), np.int64, len(distinct))
        first, count = self.first[place], self.count[place]
        sizes = count[codes]
        ids = self.flat[ragged(first[codes], sizes)]
        after = np.concatenate([[0], np.cumsum(sizes)])
        out = np.split(ids, after[ends][:-1])
        if self.end_id is None:
            return out
        end = np.array([self.end_id], np.uint32)
        return [np.concatenate([x, end]) for x in out]

    def encode(self, texts: pa.Array) -> Iterator[np.ndarray]:
        """Ids of each text in turn; null counts as empty."""
        for _, block in blocks(texts, 4_000_000):
            yield from self._block(block)


_encoders: dict[tuple, WordEncoder] = {}
caches.append(_encoders)


def shared_encoder(path: str, end_id: int | None = 1) -> WordEncoder:
    """One encoder for all tasks of a Python worker."""
    key = (path, end_id)
    if key not in _encoders:
        _encoders[key] = WordEncoder(path, end_id)
    return _encoders[key]

"""Word shingles of whole texts as 64-bit numbers, and sketches of their sets."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash

from pathalgebra.llm.words import blocks, byte_table, split_words

_LOWER = byte_table(lower=True)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads every bit (splitmix finish)."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def odd_numbers(n: int, seed: int) -> np.ndarray:
    return mix(np.arange(1, n + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(seed)) | np.uint64(1)


def shingle_sets(texts: pa.Array, width: int) -> Iterator[np.ndarray]:
    """Sorted distinct shingles of each text; null and wordless texts have none.

    Words are runs of other characters than the six blanks, with A-Z folded.  A
    text of fewer than ``width`` words has its whole sequence as one shingle.
    """
    factors = odd_numbers(width, 7)
    for _, block in blocks(texts):
        ends, codes, distinct = split_words(block, _LOWER)
        hashes = np.fromiter((xxhash.xxh3_64_intdigest(w.encode()) for w in distinct), np.uint64, len(distinct))[codes]
        rolled = np.zeros(max(0, len(hashes) - width + 1), np.uint64)
        for k in range(width):
            rolled += hashes[k : k + len(rolled)] * factors[k]
        rolled = mix(rolled)
        begin = 0
        for end in ends.tolist():
            n = end - begin
            if n >= width:
                yield np.unique(rolled[begin : end - width + 1])
            elif n:
                short = (hashes[begin:end] * factors[:n]).sum(dtype=np.uint64) + np.uint64(n)
                yield mix(np.array([short], np.uint64))
            else:
                yield np.empty(0, np.uint64)
            begin = end


class OddSketcher:
    """MinHash samples for bands, and samples folded into parity bitmaps.

    Bands take ``bands * rows`` independent MinHash values.  The bitmaps fold the
    samples of one more permutation that is dealt into bins: the least value of each
    bin that holds an element is a sample, and each sample flips the bit that it
    points to.  Two sets agree in a bin with the probability of their similarity and
    flip the same bit there, so the XOR of two bitmaps holds only what differs, and
    its population count tells how much.  A sketch holds a bitmap of ``bins`` bins,
    and for sets of at most ``small`` elements one of ``fine`` bins, where nearly
    every element is a sample.
    """

    def __init__(self, bands: int = 20, rows: int = 5, bits: int = 1024, bins: int = 1024, fine: int = 1 << 14, small: int = 1300, deviations: float = 4.0):
        if bins & (bins - 1) or fine & (fine - 1) or bits % 64:
            raise ValueError("bins must be powers of two and bits a multiple of 64")
        self.bands, self.rows, self.bits, self.bins, self.fine, self.small, self.deviations = bands, rows, bits, bins, fine, small, deviations
        self.samples = bands * rows
        self.xors, self.factors = odd_numbers(self.samples, 11), odd_numbers(self.samples, 13)
        self.lanes = odd_numbers(rows, 17)
        self.band_salt = odd_numbers(bands, 23)

    def minima(self, items: np.ndarray) -> np.ndarray:
        least = np.full(self.samples, np.iinfo(np.uint64).max, np.uint64)
        for at in range(0, len(items), 2048):
            part = items[at : at + 2048, None]
            np.minimum(least, ((part ^ self.xors) * self.factors).min(axis=0), out=least)
        return least

    def band_keys(self, minima: np.ndarray) -> np.ndarray:
        keys = (mix(minima).reshape(self.bands, self.rows) * self.lanes).sum(axis=1, dtype=np.uint64)
        return mix(keys ^ self.band_salt).view(np.int64)

    def sketch(self, items: np.ndarray) -> bytes:
        """The number of elements, those of samples in either bitmap, and the bitmaps."""
        values = np.sort(mix(items ^ np.uint64(0x5851F42D4C957F2D)))
        head, maps = [len(items)], []
        for bins in (self.fine, self.bins):
            if bins == self.fine and len(items) > self.small:
                head.append(0)
                maps.append(bytes(self.bits // 8))
                continue
            bin_of = values >> np.uint64(64 - (bins.bit_length() - 1))
            first = np.ones(len(values), bool)
            first[1:] = bin_of[1:] != bin_of[:-1]
            kept = mix(values[first])
            odd = np.bincount((kept % np.uint64(self.bits)).astype(np.int64), minlength=self.bits) & 1
            head.append(len(kept))
            maps.append(np.packbits(odd.astype(np.uint8)).tobytes())
        return np.array([*head, 0], np.uint64).tobytes() + b"".join(maps)

    def table(self, sketches) -> np.ndarray:
        """Sketches as rows of 64-bit numbers."""
        return np.frombuffer(b"".join(sketches), np.uint64).reshape(len(sketches), -1)

    def _noise(self, differ: np.ndarray) -> np.ndarray:
        """Variance of what a bitmap tells about that many differing samples, for their collisions."""
        load = np.minimum(differ / self.bits, 4)
        odd = (1 - np.exp(-2 * load)) / 2
        return self.bits * np.maximum(odd * (1 - odd) - load * np.exp(-4 * load), 0) * np.exp(4 * load)

    def similarity(self, one: np.ndarray, others: np.ndarray, percent: int) -> tuple[np.ndarray, np.ndarray]:
        """(estimated Jaccard similarity, whether it may be ``percent`` / 100) of one sketch with each other.

        The second is False only where the bitmaps differ by ``deviations`` more than
        expected at that similarity: the deviation of the bitmap's own
        collisions and that of the choice of samples.  Sizes that rule the
        similarity out by themselves do so as well.
        """
        near, may = np.zeros(len(others)), np.zeros(len(others), bool)
        both_small = (others[:, 0] <= self.small) & (one[0] <= self.small)
        for use_fine in (True, False):
            rows = np.flatnonzero(both_small == use_fine)
            if len(rows):
                near[rows], may[rows] = self._compare(one, others[rows], percent / 100, use_fine)
        sizes = np.minimum(float(one[0]), others[:, 0]) * 100 >= percent * np.maximum(float(one[0]), others[:, 0])
        return near, may & sizes

    def _compare(self, one: np.ndarray, others: np.ndarray, least: float, use_fine: bool) -> tuple[np.ndarray, np.ndarray]:
        bins, at, words = (self.fine, 4, self.bits // 64) if use_fine else (self.bins, 4 + self.bits // 64, self.bits // 64)
        elements = float(one[0]) + others[:, 0]
        column = 1 if use_fine else 2
        total = float(one[column]) + others[:, column]
        flipped = np.bitwise_count(one[at : at + words] ^ others[:, at : at + words]).sum(axis=1, dtype=np.int64)
        differ = -self.bits / 2 * np.log1p(-np.minimum(2 * flipped / self.bits, 1 - 1e-6))
        # Bins that the union of two sets of that similarity fills.
        filled = bins * -np.expm1(-elements / (1 + least) / bins)
        near = np.clip((total - differ) / 2 / np.maximum(filled, 1), 0, 1)
        wanted = np.maximum(total - 2 * least * filled, 0)
        # Where bins hold single elements, nearly all are samples and the choice is no chance.
        lost = np.maximum(elements - total, 0)
        chance = np.clip(4 * lost / np.maximum(elements, 1), 0.02, 1)
        most = wanted + self.deviations * np.sqrt(self._noise(wanted) + 4 * filled * least * (1 - least) * chance)
        # And an element that is no sample changes the difference by one at most.
        sure = elements * (1 - least) / (1 + least)
        return near, differ <= np.minimum(most, sure + lost + self.deviations * np.sqrt(self._noise(sure))) + 0.5

"""Quadtree codec of Boolean matrices: levelwise bits, rank, merges and recursion.

Each non-empty quadrant has four bits, one for each of its quadrants in the order
north-west, north-east, south-west, south-east; levels follow each other from the
root down, and a level lists its quadrants in z-order.
"""

from __future__ import annotations

import struct
from collections import Counter
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

import numpy as np

_WORD = 64


def interleave(r: np.ndarray, c: np.ndarray) -> np.ndarray:
    """z-order codes: bits of r and c in turn, r's first."""

    def spread(x: np.ndarray) -> np.ndarray:
        x = x.astype(np.uint64)
        for shift, mask in ((16, 0x0000FFFF0000FFFF), (8, 0x00FF00FF00FF00FF), (4, 0x0F0F0F0F0F0F0F0F), (2, 0x3333333333333333), (1, 0x5555555555555555)):
            x = (x | (x << np.uint64(shift))) & np.uint64(mask)
        return x

    return (spread(np.asarray(r)) << np.uint64(1)) | spread(np.asarray(c))


def deinterleave(z: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    def gather(x: np.ndarray) -> np.ndarray:
        x = x & np.uint64(0x5555555555555555)
        for shift, mask in ((1, 0x3333333333333333), (2, 0x0F0F0F0F0F0F0F0F), (4, 0x00FF00FF00FF00FF), (8, 0x0000FFFF0000FFFF), (16, 0x00000000FFFFFFFF)):
            x = (x | (x >> np.uint64(shift))) & np.uint64(mask)
        return x.astype(np.int64)

    z = np.asarray(z, np.uint64)
    return gather(z >> np.uint64(1)), gather(z)


def levels_for(side: int) -> int:
    """Levels of the smallest power of two that holds ``side`` rows."""
    return max(1, (side - 1).bit_length())


@dataclass
class QuadTree:
    levels: int
    bits: np.ndarray  # of 0 and 1
    level_bits: list[int]

    @property
    def ones(self) -> int:
        """Last-level bits that are set are the matrix's ones."""
        return int(self.bits[len(self.bits) - self.level_bits[-1] :].sum()) if self.level_bits else 0

    @property
    def nodes(self) -> int:
        return len(self.bits) // 4

    def signatures(self) -> list[list[str]]:
        out, at = [], 0
        for n in self.level_bits:
            text = "".join(map(str, self.bits[at : at + n].tolist()))
            out.append([text[k : k + 4] for k in range(0, n, 4)])
            at += n
        return out

    def to_bytes(self) -> bytes:
        head = struct.pack("<BB", self.levels, len(self.level_bits)) + np.array(self.level_bits, "<u4").tobytes()
        return head + np.packbits(self.bits).tobytes()

    @classmethod
    def from_bytes(cls, data: bytes) -> QuadTree:
        levels, n = struct.unpack_from("<BB", data)
        sizes = np.frombuffer(data, "<u4", n, 2).tolist()
        bits = np.unpackbits(np.frombuffer(data, np.uint8, offset=2 + 4 * n))[: sum(sizes)]
        return cls(levels, bits, sizes)


def encode(r, c, levels: int) -> QuadTree:
    z = np.unique(interleave(np.asarray(r), np.asarray(c)))
    if not len(z):
        return QuadTree(levels, np.zeros(0, np.uint8), [])
    parts, parents = [], np.zeros(1, np.uint64)
    for depth in range(levels):
        children = np.unique(z >> np.uint64(2 * (levels - depth - 1)))
        bits = np.zeros(4 * len(parents), np.uint8)
        where = np.searchsorted(parents, children >> np.uint64(2))
        bits[4 * where + (children & np.uint64(3)).astype(np.int64)] = 1
        parts.append(bits)
        parents = children
    return QuadTree(levels, np.concatenate(parts), [len(p) for p in parts])


def codes(tree: QuadTree) -> np.ndarray:
    """The ones as ascending z-order codes."""
    if not tree.level_bits:
        return np.zeros(0, np.uint64)
    nodes, at = np.zeros(1, np.uint64), 0
    for n in tree.level_bits:
        set_ = np.flatnonzero(tree.bits[at : at + n])
        nodes = nodes[set_ >> 2] * np.uint64(4) + (set_ & 3).astype(np.uint64)
        at += n
    return nodes


def decode(tree: QuadTree) -> tuple[np.ndarray, np.ndarray]:
    return deinterleave(codes(tree))


class RankBits:
    """Ones before a place: full sums every 2^16 bits, short sums every ``s`` words, popcounts between."""

    def __init__(self, bits: np.ndarray, s: int = 4):
        self.s, self.n = s, len(bits)
        padded = np.zeros(-(-max(1, self.n) // (1 << 16)) * (1 << 16), np.uint8)
        padded[: self.n] = bits
        self.words = np.packbits(padded, bitorder="little").view(np.uint64)
        counts = np.bitwise_count(self.words).astype(np.int64)
        before = np.concatenate([[0], np.cumsum(counts)])
        per = (1 << 16) // _WORD
        self.full = before[:-1:per]
        self.short = (before[:-1:s] - np.repeat(self.full, per // s)).astype(np.uint16)

    def rank(self, i: int) -> int:
        """Ones among the first ``i`` bits."""
        if i >= self.n:
            i = self.n
        word = i // _WORD
        if word >= len(self.words):
            return int(self.full[-1]) + int(np.bitwise_count(self.words[len(self.words) - (1 << 16) // _WORD :]).sum())
        first = word // self.s * self.s
        total = int(self.full[i >> 16]) + int(self.short[word // self.s])
        total += int(np.bitwise_count(self.words[first:word]).sum())
        rest = int(i % _WORD)
        return total + (int(self.words[word]) & ((1 << rest) - 1)).bit_count()

    def child(self, node: int, j: int) -> int:
        """Where the bits of quadrant ``j`` of the node at ``node`` begin; that quadrant isn't empty."""
        return 4 * self.rank(node + j + 1)

    def overhead_bits(self) -> float:
        return self.n / 1024 + self.n / (4 * self.s)


def has(tree: QuadTree, rank: RankBits, r: int, c: int) -> bool:
    node = 0
    if not tree.level_bits:
        return False
    for depth in range(tree.levels - 1, -1, -1):
        j = (r >> depth & 1) * 2 + (c >> depth & 1)
        if not tree.bits[node + j]:
            return False
        if depth:
            node = rank.child(node, j)
    return True


def from_codes(z: np.ndarray, levels: int) -> QuadTree:
    """The tree of ascending distinct z-order codes."""
    if not len(z):
        return QuadTree(levels, np.zeros(0, np.uint8), [])
    parts, children = [], z
    for _ in range(levels):  # from the last level up
        parents, where = np.unique(children >> np.uint64(2), return_inverse=True)
        bits = np.zeros(4 * len(parents), np.uint8)
        bits[4 * where + (children & np.uint64(3)).astype(np.int64)] = 1
        parts.append(bits)
        children = parents
    parts.reverse()
    return QuadTree(levels, np.concatenate(parts), [len(p) for p in parts])


def encode_many(keys: np.ndarray, levels: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[bytes]]:
    """Several trees at once: ``keys`` are ascending and distinct, a matrix's number above the z-order code of a one.

    Gives the numbers that occur, their ones, the bits of their levels and the trees' bytes.
    """
    keys = keys.astype(np.uint64)
    numbers, ones = np.unique(keys >> np.uint64(2 * levels), return_counts=True)
    sizes, parts, parents = np.zeros((len(numbers), levels), "<u4"), [], numbers
    for depth in range(levels):
        children = keys >> np.uint64(2 * (levels - depth - 1))
        children = children[np.concatenate([[True], children[1:] != children[:-1]])] if len(children) else children
        bits = np.zeros((len(parents), 4), np.uint8)
        bits[np.searchsorted(parents, children >> np.uint64(2)), (children & np.uint64(3)).astype(np.int64)] = 1
        owner = np.searchsorted(numbers, parents >> np.uint64(2 * depth))
        sizes[:, depth] = 4 * np.bincount(owner, minlength=len(numbers))
        parts.append((owner, bits))
        parents = children
    room = -(-sizes.sum(axis=1, dtype=np.int64) // 8)  # bytes; every tree begins at one
    first = np.cumsum(room) - room
    flat_bits, at = np.zeros((int(room.sum()) * 2, 4), np.uint8), 2 * first  # in rows of four bits
    for depth, (owner, bits) in enumerate(parts):
        n = sizes[:, depth].astype(np.int64) // 4
        flat_bits[(at - np.cumsum(n) + n)[owner] + np.arange(len(owner))] = bits
        at = at + n
    packed, head, tables = np.packbits(flat_bits.reshape(-1)).tobytes(), struct.pack("<BB", levels, levels), sizes.tobytes()
    cuts = zip(range(0, len(tables), 4 * levels), first.tolist(), (first + room).tolist(), strict=True)
    return numbers.astype(np.int64), ones, sizes, [head + tables[t : t + 4 * levels] + packed[a:b] for t, a, b in cuts]


def forest(trees: list[bytes], levels: int) -> list[np.ndarray]:
    """Level arrays of several trees that aren't empty, one tree's quadrants after the other's."""
    table_end = 2 + 4 * levels
    sizes = np.frombuffer(b"".join(t[2:table_end] for t in trees), "<u4").reshape(len(trees), levels).astype(np.int64) // 4
    bits = np.unpackbits(np.frombuffer(b"".join(t[table_end:] for t in trees), np.uint8)).reshape(-1, 4)
    room = np.array([len(t) - table_end for t in trees], np.int64) * 2
    at, out = np.cumsum(room) - room, []
    for depth in range(levels):
        n = sizes[:, depth]
        out.append(bits[np.repeat(at - np.cumsum(n) + n, n) + np.arange(int(n.sum()))])
        at = at + n
    return out


def decode_many(trees: list[bytes], levels: int) -> np.ndarray:
    """The keys of several trees that aren't empty, numbered by their places in the list."""
    nodes = np.arange(len(trees), dtype=np.uint64)
    for bits in forest(trees, levels):
        set_ = np.flatnonzero(bits)
        nodes = nodes[set_ >> 2] * np.uint64(4) + (set_ & 3).astype(np.uint64)
    return nodes


def turned_keys(keys: np.ndarray, levels: int) -> np.ndarray:
    """Keys of the transposes, not in order."""
    below = np.uint64((1 << 2 * levels) - 1)
    odd, even = np.uint64(0xAAAAAAAAAAAAAAAA) & below, np.uint64(0x5555555555555555) & below
    return (keys & ~below) | ((keys & odd) >> np.uint64(1)) | ((keys & even) << np.uint64(1))


def level_arrays(tree: QuadTree) -> list[np.ndarray]:
    """Views of the bits of each level, one row for each quadrant."""
    out, at = [], 0
    for n in tree.level_bits:
        out.append(tree.bits[at : at + n].reshape(-1, 4))
        at += n
    return out


def _from_levels(levels: int, parts: list[np.ndarray]) -> QuadTree:
    flat_parts = [p.reshape(-1) for p in parts]
    return QuadTree(levels, np.concatenate(flat_parts), [len(p) for p in flat_parts])


def quadrants(tree: QuadTree) -> list[QuadTree]:
    """The four quadrants of a tree of two levels or more; each level of one is a slice of the tree's, so nothing is decoded."""
    if tree.levels < 2:
        raise ValueError("a quadrant of a single level is a cell")
    empty_part = QuadTree(tree.levels - 1, np.zeros(0, np.uint8), [])
    if not tree.level_bits:
        return [empty_part] * 4
    rows = level_arrays(tree)
    out = []
    for j in range(4):
        if not rows[0][0, j]:
            out.append(empty_part)
            continue
        low = int(rows[0][0, :j].sum())
        high, parts = low + 1, []
        for below in rows[1:]:
            parts.append(below[low:high])
            # The children of a run of quadrants are a run of the next level.
            before = int(below[:low].sum())
            low, high = before, before + int(below[low:high].sum())
        out.append(_from_levels(tree.levels - 1, parts))
    return out


def _is_empty(tree: QuadTree) -> bool:
    return not tree.level_bits


def concat(parts: list[QuadTree], levels: int, counters: Counter | None = None) -> QuadTree:
    """The tree of four quadrants of ``levels`` - 1 levels, joined level by level.

    If one quadrant alone isn't empty, its levels are shared behind a new root.
    """
    counters = Counter() if counters is None else counters
    root = np.array([[not _is_empty(p) for p in parts]], np.uint8)
    live = [p for p in parts if not _is_empty(p)]
    if not live:
        return QuadTree(levels, np.zeros(0, np.uint8), [])
    if len(live) == 1:
        counters["trivial"] += 1
        return QuadTree(levels, np.concatenate([root.reshape(-1), live[0].bits]), [4, *live[0].level_bits])
    counters["concatenated"] += 1
    rows = [level_arrays(p) for p in live]
    return _from_levels(levels, [root, *(np.concatenate([r[d] for r in rows]) for d in range(levels - 1))])


#: Quadrants of so many levels are merged as sorted codes.
_CODE_LEVELS = 7


def combine(op: str, x: QuadTree, y: QuadTree, counters: Counter | None = None, row: int | None = None, col: int | None = None, parallel_levels: int = 0) -> QuadTree:
    """Quadrant-wise ``or``, ``and``, ``diff`` or ``xor``, each level written by itself.

    A lone operand is passed on whole: its levels are copied as slices.  ``row`` and
    ``col`` restrict the result; quadrants that miss the line count as empty.  In the
    top ``parallel_levels`` levels the quadrants are tasks of a pool of threads.
    """
    counters = Counter() if counters is None else counters
    counters["calls"] += 1
    nothing = QuadTree(x.levels, np.zeros(0, np.uint8), [])
    bound = row is not None or col is not None
    if not bound and (_is_empty(x) or _is_empty(y)):
        counters["passed"] += 1
        return {"or": y if _is_empty(x) else x, "xor": y if _is_empty(x) else x, "and": nothing, "diff": x}[op]
    if _is_empty(x) and (_is_empty(y) or op in ("and", "diff")) or (_is_empty(y) and op == "and"):
        return nothing
    if not bound and x.levels <= _CODE_LEVELS:
        a, b = codes(x), codes(y)
        z = {"or": np.union1d, "and": np.intersect1d, "diff": np.setdiff1d, "xor": np.setxor1d}[op](a, b)
        return from_codes(z.astype(np.uint64), x.levels)
    if x.levels == 1:
        a, b = (t.bits if t.level_bits else np.zeros(4, np.uint8) for t in (x, y))
        bits = {"or": a | b, "and": a & b, "diff": a & (1 - b), "xor": a ^ b}[op]
        keep = np.array([(row is None or row == j >> 1) and (col is None or col == (j & 1)) for j in range(4)], np.uint8)
        bits = bits * keep
        return QuadTree(1, bits, [4]) if bits.any() else nothing
    half = 1 << (x.levels - 1)

    def part(j: int, a: QuadTree, b: QuadTree) -> QuadTree:
        i, k = j >> 1, j & 1
        if (row is not None and (row >= half) != bool(i)) or (col is not None and (col >= half) != bool(k)):
            return QuadTree(x.levels - 1, np.zeros(0, np.uint8), [])
        return combine(op, a, b, counters, None if row is None else row - half * i, None if col is None else col - half * k, parallel_levels - 1)

    jobs = [(j, a, b) for j, (a, b) in enumerate(zip(quadrants(x), quadrants(y), strict=True))]
    if parallel_levels > 0:
        with ThreadPoolExecutor(4) as pool:
            parts = list(pool.map(lambda job: part(*job), jobs))
    else:
        parts = [part(*job) for job in jobs]
    return concat(parts, x.levels, counters)


def restrict_tree(x: QuadTree, row: int | None = None, col: int | None = None) -> QuadTree:
    """The ones of a row, a column or a cell; only quadrants on the line are looked at."""
    if row is None and col is None:
        return x
    return combine("or", x, QuadTree(x.levels, np.zeros(0, np.uint8), []), row=row, col=col)


def turned(x: QuadTree) -> QuadTree:
    """Transpose of a tree."""
    r, c = decode(x)
    return from_codes(np.sort(interleave(c, r)), x.levels)


#: Pairs of quadrants that the product holds at a time.
_PAIRS = 1 << 21


def times(x: QuadTree, y: QuadTree, counters: Counter | None = None, row: int | None = None, col: int | None = None) -> QuadTree:
    """The product by quadrants, all pairs of a level at once.

    A pair of non-empty quadrants gives up to eight pairs of the next level; a pair
    with an empty one gives none.  With ``row`` or ``col`` result quadrants that miss
    the line are left out, four of a call's eight products with one line, six with
    both.  Sums of quadrants are worked out once, at the last level.
    """
    counters = Counter() if counters is None else counters
    if _is_empty(x) or _is_empty(y):
        return QuadTree(x.levels, np.zeros(0, np.uint8), [])
    if row is None and col is None and x.levels in _DENSE_LEVELS and crowded(x.ones * y.ones, 1, x.levels):
        counters["dense"] += 1
        return from_codes(dense_codes(dense_rows(codes(x), x.levels) @ dense_rows(codes(y), x.levels) > 0), x.levels)
    start = np.zeros(1, np.int64)
    return from_codes(_products(level_arrays(x), level_arrays(y), x.levels, start, start, np.zeros(1, np.uint64), counters, row, col), x.levels)


#: Levels of matrices that may be multiplied as rows of numbers, where each result's cell has a witness or more on average.
_DENSE_LEVELS = range(5, 13)


def crowded(ones_by_ones: int, pairs: int, levels: int) -> bool:
    """Whether products of so many pairs of matrices would look at more witnesses than there are cells."""
    return ones_by_ones >> levels > pairs << 2 * levels


def dense_rows(z: np.ndarray, levels: int) -> np.ndarray:
    r, c = deinterleave(z)
    out = np.zeros((1 << levels, 1 << levels), np.float32)
    out[r, c] = 1
    return out


def dense_codes(cells: np.ndarray) -> np.ndarray:
    return np.sort(interleave(*np.nonzero(cells)))


def times_many(xs: list[bytes], ys: list[bytes], levels: int, row: int | None = None, col: int | None = None) -> np.ndarray:
    """Keys of the products of all of ``xs`` with all of ``ys``, numbered x by x; no tree is empty.

    All pairs go through the quadrants together, as those of one product do; where
    cells have a witness or more on average, matrices are multiplied as rows of numbers.
    """
    rows_x, rows_y = forest(xs, levels), forest(ys, levels)
    if row is None and col is None and levels in _DENSE_LEVELS and crowded(int(rows_x[-1].sum()) * int(rows_y[-1].sum()), len(xs) * len(ys), levels):
        right = [dense_rows(codes(QuadTree.from_bytes(y)), levels) for y in ys]
        found = []
        for i, x in enumerate(xs):
            left = dense_rows(codes(QuadTree.from_bytes(x)), levels)
            found += [dense_codes(left @ y > 0) + (np.uint64(i * len(ys) + j) << np.uint64(2 * levels)) for j, y in enumerate(right)]
        return np.concatenate(found)
    if row is None and col is None:
        x, y = decode_many(xs, levels), decode_many(ys, levels)
        if _witnesses(x, y, levels).sum() > _MANY_WITNESSES:
            return _joined(x, y, levels, len(xs), len(ys))
    number = np.arange(len(xs) * len(ys))
    return _products(rows_x, rows_y, levels, number // len(ys), number % len(ys), number.astype(np.uint64), Counter(), row, col)


#: Products with more witnesses, (row, inner line, column), are joined on the inner line, a part at a time.
_MANY_WITNESSES = 1 << 20
#: Cells of a row of results that are marked together, and witnesses that are unfolded together.
_CELLS, _UNFOLDED = 1 << 25, 1 << 22


def _places(keys: np.ndarray, levels: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(number, r, c) of the ones of several trees."""
    below = np.uint64(2 * levels)
    r, c = deinterleave(keys & np.uint64((1 << 2 * levels) - 1))
    return (keys >> below).astype(np.int64), r.astype(np.int64), c.astype(np.int64)


def _witnesses(x: np.ndarray, y: np.ndarray, levels: int) -> np.ndarray:
    """Ones of ``y`` that each one of ``x`` meets."""
    return np.bincount(_places(y, levels)[1], minlength=1 << levels)[_places(x, levels)[2]]


def _joined(x: np.ndarray, y: np.ndarray, levels: int, many_x: int, many_y: int) -> np.ndarray:
    """Ascending codes of all products, from the keys of the factors' ones; see ``times_many``.

    A left tree meets as many right ones at a time as have ``_CELLS`` cells, so what
    is held besides the result is bounded.
    """
    below, side = 2 * levels, 1 << levels
    nx, r, kx = _places(x, levels)
    group = max(1, _CELLS >> below)
    found = [[] for _ in range(many_x)]
    for first in range(0, many_y, group):
        ny, ky, c = _places(y[(y >> np.uint64(below)) // np.uint64(group) == first // group], levels)
        order = np.argsort(ky, kind="stable")
        end = interleave(np.zeros(len(c), np.int64), c).astype(np.uint64) | ((ny - first).astype(np.uint64) << np.uint64(below))
        end, degree = end[order], np.bincount(ky, minlength=side)
        start = np.cumsum(degree) - degree
        begin = interleave(r, np.zeros(len(r), np.int64)).astype(np.uint64)
        cells = min(group, many_y - first) << below
        bounds = np.searchsorted(nx, np.arange(many_x + 1))
        for i in range(many_x):
            at = slice(bounds[i], bounds[i + 1])
            meets = degree[kx[at]]
            total = int(meets.sum())
            if not total:
                continue
            grid = np.zeros(cells, bool) if total > cells >> 4 else None
            codes_of = []
            share = np.cumsum(meets) // _UNFOLDED
            cuts = [0, *(np.flatnonzero(np.diff(share)) + 1).tolist(), len(meets)]
            for a, b in zip(cuts, cuts[1:], strict=False):
                n = meets[a:b]
                place = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n) + np.repeat(start[kx[at][a:b]], n)
                unfolded = end[place] | np.repeat(begin[at][a:b], n)
                if grid is None:
                    codes_of.append(unfolded)
                else:
                    grid[unfolded.astype(np.int64)] = True
            if grid is None:
                codes = np.sort(np.concatenate(codes_of))
                codes = codes[np.concatenate([[True], codes[1:] != codes[:-1]])]
            else:
                codes = np.flatnonzero(grid).astype(np.uint64)
            found[i].append(codes + np.uint64((i * many_y + first) << below))
    parts = [p for own in found for p in own]
    return np.concatenate(parts) if parts else np.zeros(0, np.uint64)


def _products(rows_x: list[np.ndarray], rows_y: list[np.ndarray], levels: int, nx: np.ndarray, ny: np.ndarray, code: np.ndarray, counters: Counter, row: int | None, col: int | None) -> np.ndarray:
    """Ascending codes of the products of quadrants ``nx`` and ``ny`` of the first level arrays, below ``code``."""
    child_x = [np.cumsum(b.reshape(-1), dtype=np.int64) - 1 for b in rows_x]
    child_y = [np.cumsum(b.reshape(-1), dtype=np.int64) - 1 for b in rows_y]
    work = [(0, nx, ny, code)]
    found = np.zeros(0, np.uint64)
    while work:
        depth, nx, ny, code = work.pop()
        if depth == levels:
            found = np.union1d(found, code)
            continue
        if len(nx) > _PAIRS:
            work += [(depth, nx[at : at + _PAIRS], ny[at : at + _PAIRS], code[at : at + _PAIRS]) for at in range(0, len(nx), _PAIRS)]
            continue
        counters["products"] += len(nx)
        shift = levels - depth - 1
        parts = []
        for i in (0, 1) if row is None else (row >> shift & 1,):
            for j in (0, 1) if col is None else (col >> shift & 1,):
                for k in (0, 1):
                    live = (rows_x[depth][nx, 2 * i + k] & rows_y[depth][ny, 2 * k + j]).astype(bool)
                    if live.any():
                        parts.append((child_x[depth][4 * nx[live] + 2 * i + k], child_y[depth][4 * ny[live] + 2 * k + j], code[live] * np.uint64(4) + np.uint64(2 * i + j)))
        if parts:
            work.append((depth + 1, *(np.concatenate(p) for p in zip(*parts, strict=True))))
    return found


#: Levels of a matrix whose closure is worked out on rows of bits.
_LEAF_LEVELS = 8


def _closed_rows(x: QuadTree) -> QuadTree:
    r, c = decode(x)
    rows = [0] * (1 << x.levels)
    for i, j in zip(r.tolist(), c.tolist(), strict=True):
        rows[i] |= 1 << j
    for k in sorted({*c.tolist()}):
        if rows[k]:
            for i, bits in enumerate(rows):
                if bits >> k & 1:
                    rows[i] = bits | rows[k]
    out_r, out_c = [], []
    for i, bits in enumerate(rows):
        while bits:
            low = bits & -bits
            out_r.append(i)
            out_c.append(low.bit_length() - 1)
            bits ^= low
    return encode(out_r, out_c, x.levels)


def bit_rows(levels: int) -> np.ndarray:
    """An empty matrix as rows of words of bits."""
    return np.zeros((1 << levels, max(1, (1 << levels) // 64)), np.uint64)


def set_bits(rows: np.ndarray, r: np.ndarray, c: np.ndarray) -> None:
    np.bitwise_or.at(rows, (r, c // 64), np.uint64(1) << (c % 64).astype(np.uint64))


def _bits_of(words: np.ndarray) -> np.ndarray:
    return np.flatnonzero(np.unpackbits(words.view(np.uint8), bitorder="little"))


def _reached(rows: np.ndarray, start: int) -> np.ndarray:
    """What a node reaches in one or more steps, as words; every row is read once."""
    seen, fresh = rows[start].copy(), rows[start]
    while fresh.any():
        found = np.bitwise_or.reduce(rows[_bits_of(fresh)], axis=0)
        fresh = found & ~seen
        seen |= found
    return seen


def close_rows(rows: np.ndarray) -> None:
    """The closure in place: whoever reaches a node gets what that node reaches.

    The component of the node with most ones goes first and as one, since its nodes reach the same.
    """
    degree = np.bitwise_count(rows).sum(axis=1)
    start = int(degree.argmax())
    ahead = _reached(rows, start)
    done = np.zeros(0, np.int64)
    if ahead[start // 64] >> np.uint64(start % 64) & np.uint64(1):
        # Nodes that lead to the start, by rounds over those that the start leads to.
        inside, members = _bits_of(ahead), np.zeros_like(ahead)
        inside = inside[degree[inside] > 0]
        members[start // 64] |= np.uint64(1) << np.uint64(start % 64)
        while len(inside):
            hit = (rows[inside] & members).any(axis=1)
            if not hit.any():
                break
            found, inside = inside[hit], inside[~hit]
            np.bitwise_or.at(members, found // 64, np.uint64(1) << (found % 64).astype(np.uint64))
        done = _bits_of(members)
        rows[(rows & members).any(axis=1)] |= ahead
    for k in np.setdiff1d(np.flatnonzero(degree), done, assume_unique=True).tolist():
        rows[(rows[:, k // 64] >> np.uint64(k % 64) & np.uint64(1)).astype(bool)] |= rows[k]


def bands(rows: np.ndarray, band_levels: int) -> Iterator[np.ndarray]:
    """Cells of ``2^band_levels`` rows at a time."""
    for at in range(0, len(rows), 1 << band_levels):
        yield np.unpackbits(rows[at : at + (1 << band_levels)].view(np.uint8), axis=1, bitorder="little")[:, : len(rows)]


def closed_bands(z: np.ndarray, levels: int, band_levels: int) -> Iterator[np.ndarray]:
    """The closure of the matrix of z-order codes, as bands of cells."""
    rows = bit_rows(levels)
    set_bits(rows, *deinterleave(z))
    close_rows(rows)
    return bands(rows, band_levels)


def closed(x: QuadTree, counters: Counter | None = None, leaf_levels: int = _LEAF_LEVELS) -> QuadTree:
    """Closure in two passes over quadrants, on level arrays."""
    counters = Counter() if counters is None else counters
    counters["closures"] += 1
    if _is_empty(x):
        return x
    if x.levels <= max(1, leaf_levels):
        return _closed_rows(x)
    nw, ne, sw, se = quadrants(x)

    def add(a: QuadTree, b: QuadTree) -> QuadTree:
        return merge_sum(a, b)

    nw = closed(nw, counters, leaf_levels)
    ne, sw_low = add(ne, times(nw, ne, counters)), add(sw, times(sw, nw, counters))
    se = closed(add(se, times(sw, ne, counters)), counters, leaf_levels)
    sw, ne = add(sw_low, times(se, sw_low, counters)), add(ne, times(ne, se, counters))
    nw = add(nw, times(ne, sw_low, counters))
    return concat([nw, ne, sw, se], x.levels)


def merge_sum(x: QuadTree, y: QuadTree, batch_copies: bool = True, counters: Counter | None = None) -> QuadTree:
    """Sum in one pass over both bit strings.

    A level's tasks, in order, each merge two signatures or copy one; they name the
    next level's tasks.  With ``batch_copies`` a level's copies from one side are one
    block of words, and so are its merges; without it every signature is handled by
    itself, as libraries do that copy node by node.
    """
    counters = Counter() if counters is None else counters
    if not x.level_bits or not y.level_bits:
        return x if x.level_bits else y
    tasks = np.array([3], np.int8)  # 1: from x, 2: from y, 3: both
    parts = []
    for rows_x, rows_y in zip(level_arrays(x), level_arrays(y), strict=True):
        counters["tasks"] += len(tasks)
        counters["merges"] += int((tasks == 3).sum())
        copies = tasks != 3
        if batch_copies:
            counters["copies"] += int((copies & np.concatenate([[True], tasks[1:] != tasks[:-1]])).sum())
            kinds = np.zeros((len(tasks), 4), np.uint8)
            kinds[(tasks & 1) > 0] = rows_x
            kinds[(tasks & 2) > 0] += 2 * rows_y
        else:
            counters["copies"] += int(copies.sum())
            kinds = np.empty((len(tasks), 4), np.uint8)
            ax = ay = 0
            for k, task in enumerate(tasks.tolist()):
                if task == 3:
                    kinds[k] = rows_x[ax] + 2 * rows_y[ay]
                else:
                    kinds[k] = rows_x[ax] if task == 1 else 2 * rows_y[ay]
                ax += task & 1
                ay += task >> 1
        parts.append((kinds > 0).astype(np.uint8))
        flat_kinds = kinds.reshape(-1)
        tasks = flat_kinds[flat_kinds > 0].astype(np.int8)
    return _from_levels(x.levels, parts)


# Recursion works on nested quadrants: None is empty, True a single one, else four parts.
Nested = None | bool | tuple


def nest(tree: QuadTree) -> Nested:
    z = codes(tree)
    return _nest(z, tree.levels)


def _nest(z: np.ndarray, levels: int) -> Nested:
    if not len(z):
        return None
    if not levels:
        return True
    top = (z >> np.uint64(2 * (levels - 1))) & np.uint64(3)
    cuts = np.searchsorted(top, [0, 1, 2, 3, 4])
    return tuple(_nest(z[a:b], levels - 1) for a, b in zip(cuts, cuts[1:], strict=False))


def flat(q: Nested, levels: int) -> QuadTree:
    found: list[int] = []

    def visit(x: Nested, code: int) -> None:
        if x is True:
            found.append(code)
        elif x is not None:
            for j, part in enumerate(x):
                visit(part, code * 4 + j)

    visit(q, 0)
    r, c = deinterleave(np.array(found, np.uint64))
    return encode(r, c, levels)


def _join(parts: tuple) -> Nested:
    return None if all(p is None for p in parts) else parts


def recurse(op: str, x: Nested, y: Nested, counters: Counter | None = None) -> Nested:
    """Quadrant-wise ``or``, ``and``, ``diff`` or ``xor``; a lone operand is passed on whole."""
    counters = Counter() if counters is None else counters
    counters["calls"] += 1
    if x is None or y is None:
        counters["passed"] += 1
        return {"or": y if x is None else x, "xor": y if x is None else x, "and": None, "diff": x}[op]
    if x is True:
        return True if op in ("or", "and") else None
    return _join(tuple(recurse(op, a, b, counters) for a, b in zip(x, y, strict=True)))


def flip(x: Nested) -> Nested:
    """Transpose: north-east and south-west change places at every level."""
    return x if x is None or x is True else (flip(x[0]), flip(x[2]), flip(x[1]), flip(x[3]))


def multiply(x: Nested, y: Nested, counters: Counter | None = None, row: int | None = None, col: int | None = None, levels: int = 0) -> Nested:
    """Eight products and four sums of quadrants; an empty factor ends a branch.

    ``row`` and ``col`` restrict the result; quadrants that miss the line count as
    empty, so at most four products of a call are left with one line, two with both.
    """
    counters = Counter() if counters is None else counters
    if x is None or y is None:
        return None
    counters["products"] += 1
    if x is True:
        return True
    half = 1 << (levels - 1) if levels > 0 else 0

    def of(i: int, j: int) -> Nested:
        if (row is not None and (row >= half) != bool(i)) or (col is not None and (col >= half) != bool(j)):
            return None
        r = None if row is None else row - half * i
        c = None if col is None else col - half * j
        a = multiply(x[2 * i], y[j], counters, r, c, levels - 1)
        b = multiply(x[2 * i + 1], y[2 + j], counters, r, c, levels - 1)
        return recurse("or", a, b, counters)

    return _join((of(0, 0), of(0, 1), of(1, 0), of(1, 1)))


def tree_closure(x: Nested, counters: Counter | None = None) -> Nested:
    """Two passes over quadrants, as in the distributed form."""
    counters = Counter() if counters is None else counters
    if x is None or x is True:
        return x

    def add(a: Nested, b: Nested) -> Nested:
        return recurse("or", a, b, counters)

    def times(a: Nested, b: Nested) -> Nested:
        return multiply(a, b, counters)

    nw, ne, sw, se = x
    nw = tree_closure(nw, counters)
    ne = add(ne, times(nw, ne))
    se = add(se, times(sw, ne))
    sw = add(sw, times(sw, nw))
    se = tree_closure(se, counters)
    low = sw
    sw = add(sw, times(se, sw))
    ne = add(ne, times(ne, se))
    nw = add(nw, times(ne, low))
    return _join((nw, ne, sw, se))


def size_bound_bits(ones: int, side: int) -> float:
    """Upper bound of the bits: 4 a log4(side^2 / a) + 4 a / 3 + O(1)."""
    return 4 * ones * np.log2(max(1.0, side * side / ones)) / 2 + 4 * ones / 3 + 4 * levels_for(side) if ones else 0.0

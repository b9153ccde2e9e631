"""Matrices as tables of tiles: the top of the quadtree is the key, the rest a payload.

A tile covers ``2^tile_bits`` rows and columns.  Sums join tiles by place and pass
lonely ones on untouched; products join on the inner index and merge what lands
on one tile; closures go through quadrants of tiles in two passes.  Transposition
exchanges the two keys and turns a flag over; payloads are turned where one meets a
payload that isn't flipped.  Node numbers must be dense, see
``sources.graphs.dense_numbers``.
"""

from __future__ import annotations

from collections.abc import Generator, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathalgebra.operators import quadtree as qt
from pathalgebra.operators.components import FactoredClosure, factored_closure, saturated
from pathalgebra.runtime import checkpointed

TILE = "tr int, tc int, ones int, level_bits array<int>, bits binary, flipped boolean"
_PAYLOAD = ("ones", "level_bits", "bits", "flipped")


#: Ones that a task decodes at a time.
_ONES = 1 << 22
#: Two tiles with more ones are summed by themselves.
_FULL_ONES = 1 << 12


def _frame(tr, tc, ones, level_bits, bits, flipped=False) -> pd.DataFrame:
    return pd.DataFrame({"tr": tr, "tc": tc, "ones": ones, "level_bits": list(level_bits), "bits": bits, "flipped": flipped})


def _frame_of(rows: list[tuple[int, int, qt.QuadTree, bool]]) -> pd.DataFrame:
    """Tiles of one batch; a frame for each tile would cost far more than the tile."""
    tr, tc, trees, flipped = zip(*rows, strict=True)
    return _frame(tr, tc, [t.ones for t in trees], [t.level_bits for t in trees], [t.to_bytes() for t in trees], list(flipped))


def _tree(bits: bytes, flipped: bool) -> qt.QuadTree:
    tree = qt.QuadTree.from_bytes(bits)
    return qt.turned(tree) if flipped else tree


def _numbers(tr: np.ndarray, tc: np.ndarray) -> np.ndarray:
    """Numbers of runs of equal places."""
    return np.cumsum(np.concatenate([[False], (tr[1:] != tr[:-1]) | (tc[1:] != tc[:-1])]))


def _encoded(tr: np.ndarray, tc: np.ndarray, number: np.ndarray, z: np.ndarray, levels: int) -> pd.DataFrame:
    """Tiles of ones at places in order, given by the run of each one."""
    first = np.flatnonzero(np.concatenate([[True], number[1:] != number[:-1]])) if len(number) else number
    _, ones, sizes, trees = qt.encode_many(np.unique((number.astype(np.uint64) << np.uint64(2 * levels)) | z), levels)
    return _frame(tr[first], tc[first], ones, sizes.tolist(), trees)


def _shares(ones: np.ndarray) -> Iterator[slice]:
    """Slices of a batch with about ``_ONES`` ones each, or one tile; bounds of the ones do as well."""
    if not len(ones):
        return iter(())
    share = np.cumsum(ones, dtype=np.int64) // _ONES
    cuts = [0, *(np.flatnonzero(np.diff(share)) + 1).tolist(), len(ones)]
    return (slice(a, b) for a, b in zip(cuts, cuts[1:], strict=False) if b > a)


def _keys(trees: list[bytes], levels: int, turn: np.ndarray | None = None) -> np.ndarray:
    """Ascending keys of all tiles of a batch, numbered by their places in the list; those under ``turn`` are turned, empty ones have none."""
    place = np.flatnonzero([t[1] > 0 for t in trees])  # levels that are stored
    if not len(place):
        return np.zeros(0, np.uint64)
    keys = qt.decode_many([trees[i] for i in place.tolist()], levels)
    below = np.uint64(2 * levels)
    number = place[(keys >> below).astype(np.int64)]
    keys = (number.astype(np.uint64) << below) | (keys & np.uint64((1 << 2 * levels) - 1))
    if turn is not None and turn[number].any():
        keys = np.sort(np.where(turn[number], qt.turned_keys(keys, levels), keys))
    return keys


def to_tiles(a: DataFrame, tile_bits: int = 10) -> DataFrame:
    """(tr, tc, ones, level_bits, bits, flipped) from (r, c); a task encodes all tiles of a batch together."""
    mask = (1 << tile_bits) - 1

    def pack(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: list[pd.DataFrame] = []  # the last place's rows, as more may follow
        for f in frames:
            if not len(f):
                continue
            tr, tc = f["tr"].to_numpy(), f["tc"].to_numpy()
            if held and (tr[-1], tc[-1]) == (held[0]["tr"].iloc[0], held[0]["tc"].iloc[0]):
                held.append(f)
                continue
            last = int(np.argmax((tr == tr[-1]) & (tc == tc[-1])))  # places are in order
            if held or last:
                yield packed(pd.concat([*held, f.iloc[:last]]))
            held = [f.iloc[last:]]
        if held:
            yield packed(pd.concat(held))

    def packed(f: pd.DataFrame) -> pd.DataFrame:
        tr, tc = f["tr"].to_numpy(), f["tc"].to_numpy()
        return _encoded(tr, tc, _numbers(tr, tc), qt.interleave(f["r"].to_numpy() & mask, f["c"].to_numpy() & mask), tile_bits)

    keyed = a.select(F.shiftright("r", tile_bits).cast("int").alias("tr"), F.shiftright("c", tile_bits).cast("int").alias("tc"), "r", "c")
    return keyed.repartition("tr", "tc").sortWithinPartitions("tr", "tc").mapInPandas(pack, TILE)


#: Tiles with so many ones get the terms of their rows and columns as arrays.
_TERMS_ONES = 512


def _dealt(rows: DataFrame) -> DataFrame:
    """Rows whose work is far larger than they are, dealt evenly: by their bytes Spark would give them to one task."""
    return rows.repartition(4 * int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")))


def from_tiles(tiles: DataFrame, tile_bits: int = 10, names: DataFrame | None = None) -> DataFrame:
    """(r, c) of all ones; with ``names`` (term, id) as terms in place of dense numbers.

    Full tiles meet the terms of their lines, as arrays, before they are unpacked, so
    that no join looks at their ones; the ones of other tiles are joined.
    """
    if names is not None:
        tiles = checkpointed(tiles)
        block = names.groupBy(F.shiftright("id", tile_bits).cast("int").alias("t")).agg(F.array_sort(F.collect_list(F.struct("id", "term"))).alias("n")).select("t", F.col("n.term").alias("terms"))
        full = tiles.where(F.col("ones") >= _TERMS_ONES).select("tr", "tc", "bits", "flipped")
        any_full = not full.isEmpty()
        full = full.join(block.select(F.col("t").alias("tr"), F.col("terms").alias("row_terms")), "tr").join(block.select(F.col("t").alias("tc"), F.col("terms").alias("col_terms")), "tc")
        full = _dealt(full)
        few = from_tiles(tiles.where(F.col("ones") < _TERMS_ONES), tile_bits)
        few = few.join(names.select(F.col("id").alias("r"), F.col("term").alias("x")), "r").join(names.select(F.col("id").alias("c"), F.col("term").alias("y")), "c")
        if not any_full:
            return few.select(F.col("x").alias("r"), F.col("y").alias("c"))
        return full.select("tr", "tc", "bits", "flipped", "row_terms", "col_terms").mapInPandas(_unpacker(tile_bits), "r long, c long").union(few.select("x", "y"))
    return tiles.select("tr", "tc", "bits", "flipped").mapInPandas(_unpacker(tile_bits), "r long, c long")


def _unpacker(tile_bits: int):
    def unpack(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            f = f[[x[1] > 0 for x in f["bits"]]]  # levels that are stored; an empty tree has none
            for s in _shares(np.array([8 * len(x) for x in f["bits"]], np.int64)):
                part = f.iloc[s]
                keys = qt.decode_many(part["bits"].tolist(), tile_bits)
                at = (keys >> np.uint64(2 * tile_bits)).astype(np.int64)
                r, c = qt.deinterleave(keys & np.uint64((1 << 2 * tile_bits) - 1))
                flipped = part["flipped"].to_numpy(bool)[at]
                r, c = np.where(flipped, c, r), np.where(flipped, r, c)
                if "row_terms" in part:
                    yield pd.DataFrame({"r": _terms(part["row_terms"], at, r), "c": _terms(part["col_terms"], at, c)})
                    continue
                tr, tc = part["tr"].to_numpy(np.int64)[at], part["tc"].to_numpy(np.int64)[at]
                yield pd.DataFrame({"r": r + (tr << tile_bits), "c": c + (tc << tile_bits)})

    return unpack


def _terms(arrays: pd.Series, at: np.ndarray, place: np.ndarray) -> np.ndarray:
    sizes = np.array([len(x) for x in arrays], np.int64)
    return np.concatenate(arrays.tolist())[(np.cumsum(sizes) - sizes)[at] + place]


def tile_identity(nodes: DataFrame, tile_bits: int = 10) -> DataFrame:
    """Ones at (id, id)."""
    return to_tiles(nodes.select(F.col("id").alias("r"), F.col("id").alias("c")), tile_bits)


def tile_transpose(tiles: DataFrame) -> DataFrame:
    """Exchanges names and turns a flag over; no payload is read."""
    return tiles.select(F.col("tc").alias("tr"), F.col("tr").alias("tc"), "ones", "level_bits", "bits", (~F.col("flipped")).alias("flipped"))


def _on_line(tiles: DataFrame, row: int | None, col: int | None, tile_bits: int) -> DataFrame:
    """The tiles that a restriction can touch: a filter on their keys."""
    if row is not None:
        tiles = tiles.where(F.col("tr") == row >> tile_bits)
    return tiles if col is None else tiles.where(F.col("tc") == col >> tile_bits)


def tile_restrict(tiles: DataFrame, row: int | None = None, col: int | None = None, tile_bits: int = 10) -> DataFrame:
    """The ones of a row, a column or a cell; other tiles are filtered by their keys."""
    if row is None and col is None:
        return tiles
    mask = (1 << tile_bits) - 1
    r, c = None if row is None else row & mask, None if col is None else col & mask

    def cut(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            for s in _shares(f["ones"].to_numpy()):
                part = f.iloc[s]
                flipped = part["flipped"].to_numpy(bool)
                keys = _keys(part["bits"].tolist(), tile_bits)
                at = (keys >> np.uint64(2 * tile_bits)).astype(np.int64)
                own_r, own_c = qt.deinterleave(keys & np.uint64((1 << 2 * tile_bits) - 1))
                own_r, own_c = np.where(flipped[at], own_c, own_r), np.where(flipped[at], own_r, own_c)
                keys = keys[((r is None) | (own_r == r)) & ((c is None) | (own_c == c))]
                if len(keys):
                    number, ones, sizes, trees = qt.encode_many(keys, tile_bits)
                    yield _frame(part["tr"].to_numpy()[number], part["tc"].to_numpy()[number], ones, sizes.tolist(), trees, flipped[number])

    return _on_line(tiles, row, col, tile_bits).mapInPandas(cut, TILE)


def tile_has(tiles: DataFrame, row: int, col: int, tile_bits: int = 10) -> bool:
    """Whether a cell of a stored matrix holds a one: one tile is read, and probed by rank."""
    mask = (1 << tile_bits) - 1

    def probe(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            for bits, flipped in zip(f["bits"], f["flipped"], strict=True):
                tree = qt.QuadTree.from_bytes(bits)
                r, c = (col & mask, row & mask) if flipped else (row & mask, col & mask)
                yield pd.DataFrame({"hit": [qt.has(tree, qt.RankBits(tree.bits), r, c)]})

    return not _on_line(tiles, row, col, tile_bits).mapInPandas(probe, "hit boolean").where("hit").isEmpty()


def tile_sum(a: DataFrame, b: DataFrame, op: str = "or", row: int | None = None, col: int | None = None, tile_bits: int = 10) -> DataFrame:
    """``or``, ``and``, ``diff`` or ``xor`` of two tile tables, in one row or column if asked."""
    a, b = (tile_restrict(x, row, col, tile_bits) for x in (a, b))
    left = a.select("tr", "tc", F.struct(*_PAYLOAD).alias("a"))
    right = b.select("tr", "tc", F.struct(*_PAYLOAD).alias("b"))
    joined = left.join(right, ["tr", "tc"], "full_outer")
    alone = joined.where("a is null or b is null")
    alone = alone.where({"or": "true", "xor": "true", "and": "false", "diff": "a is not null"}[op])
    passed = alone.select("tr", "tc", F.coalesce("a", "b").alias("t")).select("tr", "tc", "t.ones", "t.level_bits", "t.bits", "t.flipped")

    def merge(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            # Full tiles are summed level by level; others are taken together, as each alone would cost more than its ones.
            full = (f["n"] > _FULL_ONES).to_numpy() if op == "or" else np.zeros(len(f), bool)
            out = []
            for tr, tc, x, y, fx, fy in zip(*(f.loc[full, k] for k in ("tr", "tc", "x", "y", "fx", "fy")), strict=True):
                # Two flipped payloads are merged as they are, and the result is flipped.
                out.append((tr, tc, qt.merge_sum(_tree(x, fx and not fy), _tree(y, fy and not fx)), fx and fy))
            if out:
                yield _frame_of(out)
            rest = f[~full]
            for s in _shares(rest["n"].to_numpy()):
                part = rest.iloc[s]
                fx, fy, levels = part["fx"].to_numpy(bool), part["fy"].to_numpy(bool), part["x"].iloc[0][0]
                a, b = _keys(part["x"].tolist(), levels, fx & ~fy), _keys(part["y"].tolist(), levels, fy & ~fx)
                keys = np.union1d(a, b) if op == "or" else {"and": np.intersect1d, "diff": np.setdiff1d, "xor": np.setxor1d}[op](a, b, assume_unique=True)
                if len(keys):
                    number, ones, sizes, trees = qt.encode_many(keys, levels)
                    yield _frame(part["tr"].to_numpy()[number], part["tc"].to_numpy()[number], ones, sizes.tolist(), trees, (fx & fy)[number])

    both = joined.where("a is not null and b is not null")
    both = both.select("tr", "tc", F.col("a.bits").alias("x"), F.col("b.bits").alias("y"), F.col("a.flipped").alias("fx"), F.col("b.flipped").alias("fy"), F.expr("cast(a.ones as long) + b.ones").alias("n"))
    return passed.unionByName(both.mapInPandas(merge, TILE))


#: A strip of tiles with one inner key has so many tiles and about so many ones at most, so a pair of strips is bounded work.
_STRIP_TILES, _STRIP_ONES = 512, 1 << 14


def _strips(tiles: DataFrame, inner: str, outer: str, name: str) -> DataFrame:
    """(k, name, name_bits, name_flipped): the tiles of an inner key dealt into bounded arrays."""
    loads = tiles.groupBy(F.col(inner).alias("k")).agg(F.ceil(F.greatest(F.sum("ones") / _STRIP_ONES, F.count("*") / _STRIP_TILES)).cast("int").alias("strips"))
    dealt = tiles.select(F.col(inner).alias("k"), F.struct(F.col(outer).alias("at"), "bits", "flipped").alias("t")).join(loads, "k")
    rows = dealt.groupBy("k", F.pmod(F.xxhash64("t.at"), F.col("strips")).alias("strip")).agg(F.collect_list("t").alias("t"))
    return rows.select("k", F.col("t.at").alias(name), F.col("t.bits").alias(f"{name}_bits"), F.col("t.flipped").alias(f"{name}_flipped"))


def _turned_back(trees: list[bytes], flipped: list[bool], levels: int) -> list[bytes]:
    """Payloads as they stand, the flipped ones turned."""
    where = [i for i, f in enumerate(flipped) if f]
    if where:
        trees = list(trees)
        for i, t in zip(where, qt.encode_many(np.sort(qt.turned_keys(qt.decode_many([trees[i] for i in where], levels), levels)), levels)[3], strict=True):
            trees[i] = t
    return trees


#: A pair of strips with more witnesses, (row, inner line, column), is multiplied by itself.
_FEW_WITNESSES = 1 << 16


def _strip_ones(f: pd.DataFrame, side: str, levels: int) -> tuple[np.ndarray, ...]:
    """(pair of strips, outer key, r, c) of all ones of one side."""
    sizes = np.array([len(x) for x in f[side]], np.int64)
    trees, outer, flipped = ([v for x in f[k] for v in x] for k in (f"{side}_bits", side, f"{side}_flipped"))
    keys = _keys(trees, levels, np.array(flipped, bool))
    at = (keys >> np.uint64(2 * levels)).astype(np.int64)
    r, c = qt.deinterleave(keys & np.uint64((1 << 2 * levels) - 1))
    return np.repeat(np.arange(len(f)), sizes)[at], np.array(outer, np.int64)[at], r, c


def _multiplied(f: pd.DataFrame) -> Generator[pd.DataFrame, None, np.ndarray]:
    """Products of pairs of strips of few witnesses, joined on the inner line all together, as each pair alone would cost more than its ones.

    Returns which of the pairs are left as they have more.
    """
    levels = f["x_bits"].iloc[0][0][0]
    (px, tr, r, kx), (py, tc, ky, c) = _strip_ones(f, "x", levels), _strip_ones(f, "y", levels)
    inner = py << levels | ky
    order = np.argsort(inner, kind="stable")
    inner, tc, c = inner[order], tc[order], c[order]
    start = np.searchsorted(inner, px << levels | kx)
    meets = np.searchsorted(inner, px << levels | kx, "right") - start
    many = np.bincount(px, meets, len(f)) > _FEW_WITNESSES
    live = np.flatnonzero((meets > 0) & ~many[px])
    share = np.cumsum(meets[live]) // (16 * _FEW_WITNESSES)
    for own in np.split(live, np.flatnonzero(np.diff(share)) + 1) if len(live) else ():
        n = meets[own]
        y = np.arange(int(n.sum())) + np.repeat(start[own] - np.cumsum(n) + n, n)
        x = np.repeat(own, n)
        places, number = np.unique(tr[x] << 32 | tc[y], return_inverse=True)
        keys = np.unique(number.astype(np.uint64) << np.uint64(2 * levels) | qt.interleave(r[x], c[y]))
        _, ones, sizes, trees = qt.encode_many(keys, levels)
        yield _frame(places >> 32, places & 0xFFFFFFFF, ones, sizes.tolist(), trees)
    return many


def _merged(tiles: DataFrame) -> DataFrame:
    """One tile for each place, the sum of all there; none is flipped."""

    def total(f: pd.DataFrame) -> pd.DataFrame:
        """Places that have one tile keep it as it is."""
        runs = _numbers(f["tr"].to_numpy(), f["tc"].to_numpy())
        alone = np.bincount(runs)[runs] == 1
        if alone.all():
            return f
        if not alone.any():
            return summed(f)
        order = np.argsort(np.concatenate([runs[alone], np.unique(runs[~alone])]))
        return pd.concat([f[alone], summed(f[~alone])], ignore_index=True).iloc[order]

    def summed(f: pd.DataFrame) -> pd.DataFrame:
        tr, tc, levels = f["tr"].to_numpy(), f["tc"].to_numpy(), f["bits"].iloc[0][0]
        keys = qt.decode_many(f["bits"].tolist(), levels)
        below, runs = np.uint64(2 * levels), _numbers(tr, tc)
        number, z = runs[(keys >> below).astype(np.int64)], keys & np.uint64((1 << 2 * levels) - 1)
        first = np.flatnonzero(np.concatenate([[True], runs[1:] != runs[:-1]]))
        keys = (number.astype(np.uint64) << below) | z
        cells = len(first) << 2 * levels
        if len(keys) > cells >> 4 and cells <= 8 * _ONES:
            grid = np.zeros(cells, bool)
            grid[keys.astype(np.int64)] = True
            keys = np.flatnonzero(grid)
        else:
            keys = np.unique(keys)
        _, ones, sizes, trees = qt.encode_many(keys, levels)
        return _frame(tr[first], tc[first], ones, sizes.tolist(), trees)

    def merge(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held = None
        for f in frames:
            for s in _shares(f["ones"].to_numpy()):
                part = f.iloc[s] if held is None else pd.concat([held, f.iloc[s]])
                part = total(part)
                if len(part) > 1:
                    yield part.iloc[:-1]
                held = part.iloc[-1:]
        if held is not None:
            yield held

    return tiles.repartition("tr", "tc").sortWithinPartitions("tr", "tc").mapInPandas(merge, TILE)


def tile_product(a: DataFrame, b: DataFrame, row: int | None = None, col: int | None = None, tile_bits: int = 10, few_inner: bool = False) -> DataFrame:
    """Tiles of the product; a result tile is merged from partial ones of the same place.

    Tiles of one inner key meet as strips, and all pairs of two strips go through
    their quadrants together.  A restriction filters the tiles of the left factor's
    row or the right factor's column and goes on inside the quadrants of those left.
    With ``few_inner`` keys the pairs of strips are dealt evenly, as those of a key share a task otherwise.
    """
    mask = (1 << tile_bits) - 1
    r, c = None if row is None else row & mask, None if col is None else col & mask

    def multiply(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            if r is None and c is None:
                crowded = []
                for s in _shares(np.array([8 * (sum(map(len, x)) + sum(map(len, y))) for x, y in zip(f["x_bits"], f["y_bits"], strict=True)], np.int64)):
                    many = yield from _multiplied(f.iloc[s])
                    crowded += (np.flatnonzero(many) + s.start).tolist()
                f = f.iloc[crowded]
            for tr, x, fx, tc, y, fy in zip(f["x"], f["x_bits"], f["x_flipped"], f["y"], f["y_bits"], f["y_flipped"], strict=True):
                levels = x[0][0]  # a payload begins with its levels
                keys = qt.times_many(_turned_back(list(x), fx, levels), _turned_back(list(y), fy, levels), levels, r, c)
                if len(keys):
                    number, ones, sizes, trees = qt.encode_many(keys, levels)
                    yield _frame(np.asarray(tr)[number // len(tc)], np.asarray(tc)[number % len(tc)], ones, sizes.tolist(), trees)

    a, b = _on_line(a, row, None, tile_bits).where("ones > 0"), _on_line(b, None, col, tile_bits).where("ones > 0")
    pairs = _strips(a, "tc", "tr", "x").join(_strips(b, "tr", "tc", "y"), "k")
    pairs = pairs.select("x", "x_bits", "x_flipped", "y", "y_bits", "y_flipped")
    return _merged((_dealt(pairs) if few_inner else pairs).mapInPandas(multiply, TILE))


#: Nodes of a range of tiles that one task closes, as rows of bits: 32 MB.
_LEAF_SIDE = 1 << 14


def _leaf_ranges(tiles: DataFrame, level: int, bits: int) -> DataFrame:
    """Closures of aligned ranges of 2^``level`` tiles, each in one task."""

    def closed(parts: list[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        low = int(parts[0]["range"].iloc[0]) << level
        rows = qt.bit_rows(bits + level)
        for f in parts:
            for s in _shares(f["ones"].to_numpy()):
                part = f.iloc[s]
                keys = _keys(part["bits"].tolist(), bits, part["flipped"].to_numpy(bool))
                at = (keys >> np.uint64(2 * bits)).astype(np.int64)
                r, c = qt.deinterleave(keys & np.uint64((1 << 2 * bits) - 1))
                qt.set_bits(rows, r + ((part["tr"].to_numpy(np.int64) - low)[at] << bits), c + ((part["tc"].to_numpy(np.int64) - low)[at] << bits))
        qt.close_rows(rows)
        # A row of tiles at a time, so what is unpacked is a band of the matrix.
        for tr, band in enumerate(qt.bands(rows, bits)):
            r, c = np.nonzero(band)
            if len(r):
                keys = np.sort((c >> bits).astype(np.uint64) << np.uint64(2 * bits) | qt.interleave(r, c & ((1 << bits) - 1)))
                number, ones, sizes, trees = qt.encode_many(keys, bits)
                yield _frame(np.full(len(number), tr + low), number + low, ones, sizes.tolist(), trees)

    def close(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: list[pd.DataFrame] = []  # of one range, as more may follow
        for f in frames:
            of = f["range"].to_numpy()
            cuts = [0, *(np.flatnonzero(np.diff(of)) + 1).tolist(), len(of)]
            for x, y in zip(cuts, cuts[1:], strict=False):
                if y > x and held and held[0]["range"].iloc[0] != of[x]:
                    yield from closed(held)
                    held = []
                if y > x:
                    held.append(f.iloc[x:y])
        if held:
            yield from closed(held)

    ranged = tiles.where("ones > 0").withColumn("range", F.shiftright("tr", level))
    return ranged.repartition("range").sortWithinPartitions("range").mapInPandas(close, TILE)


def tile_closure(tiles: DataFrame) -> DataFrame:
    """Closure in two passes over quadrants of tiles; a range of few nodes is closed in a task."""
    tiles = checkpointed(tiles.where("ones > 0"))
    high, bits = tiles.agg(F.max(F.greatest("tr", "tc")), F.max(F.size("level_bits"))).first()
    if bits is None:
        return tiles
    level = high.bit_length()
    return _close_ranges(tiles, level, min(level, max(0, (_LEAF_SIDE >> bits).bit_length() - 1)), bits)


def closed_pairs(tiles: DataFrame, tile_bits: int = 10, names: DataFrame | None = None) -> DataFrame:
    """(r, c) of the closure of a tile table, as from ``from_tiles``.

    Where components make many pairs, these are expanded by blocks of members: full
    tiles would be multiplied, written and unpacked one by one.
    """
    tiles = checkpointed(tiles.where("ones > 0"))
    ones = checkpointed(from_tiles(tiles, tile_bits))
    comp = saturated(ones, _ones(tiles))
    if comp is None:
        return from_tiles(tile_closure(tiles), tile_bits, names)
    closure = factored_closure(ones, comp=comp)
    if names is not None:
        closure = FactoredClosure(checkpointed(comp.join(names, "id").select(F.col("term").alias("id"), "comp")), closure.reach, closure.cyclic)
    return closure.pairs()


def _close_ranges(tiles: DataFrame, level: int, leaf: int, bits: int) -> DataFrame:
    """Closures of all aligned ranges of 2^``level`` tiles side by side; every tile has both keys in one range.

    Tiles of different ranges never meet in a product, so a step is taken for all
    ranges at once.  Where ones lead from one half to the other but not back, both
    halves are closed together; only other ranges close their second half after the first.
    """
    if level <= leaf:
        return checkpointed(_leaf_ranges(tiles, leaf, bits))
    half = level - 1
    rows, cols = f"shiftright(tr, {half})", f"shiftright(tc, {half})"
    flags = tiles.groupBy(F.shiftright("tr", level).alias("range")).agg(F.max(F.expr(f"{rows} < {cols}")).alias("up"), F.max(F.expr(f"{rows} > {cols}")).alias("down"))
    apart, both, every = flags.agg(F.max(F.expr("up or down")), F.count_if(F.expr("up and down")), F.count("*")).first()
    if not apart:
        return _close_ranges(tiles, half, leaf, bits)

    def add(a: DataFrame, b: DataFrame) -> DataFrame:
        return checkpointed(tile_sum(a, b))

    def whole(*parts: DataFrame) -> DataFrame:
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return checkpointed(out.coalesce(int(tiles.sparkSession.conf.get("spark.sql.shuffle.partitions"))))

    def one_way(diagonal: DataFrame, off: DataFrame) -> DataFrame:
        off = add(off, tile_product(off, diagonal))
        return add(off, tile_product(diagonal, off))

    on, off = f"{rows} = {cols}", f"{rows} <> {cols}"
    if not both:
        diagonal = _close_ranges(tiles.where(on), half, leaf, bits)
        return whole(diagonal, one_way(diagonal, tiles.where(off)))
    mutual = checkpointed(flags.where("up and down").select("range"))

    def among(x: DataFrame, how: str) -> DataFrame:
        if both == every:
            return x if how == "left_semi" else x.where("false")
        return checkpointed(x.join(mutual, F.shiftright("tr", level) == mutual["range"], how))

    pair, single = among(tiles, "left_semi"), among(tiles, "left_anti")

    def part(i: int, j: int) -> DataFrame:
        return pair.where(f"({rows} & 1) = {i} and ({cols} & 1) = {j}")

    ne, sw = part(0, 1), part(1, 0)
    first = _close_ranges(part(0, 0).unionByName(single.where(on)), half, leaf, bits)
    nw, alone = among(first, "left_semi"), among(first, "left_anti")
    ne, sw_low = add(ne, tile_product(nw, ne)), add(sw, tile_product(sw, nw))
    se = _close_ranges(add(part(1, 1), tile_product(sw, ne)), half, leaf, bits)
    sw, ne = add(sw_low, tile_product(se, sw_low)), add(ne, tile_product(ne, se))
    nw = add(nw, tile_product(ne, sw_low))
    if both == every:
        return whole(nw, ne, sw, se)
    return whole(nw, ne, sw, se, alone, one_way(alone, single.where(off)))


def tile_round_trips(a: DataFrame, b: DataFrame, tile_bits: int = 10) -> DataFrame | None:
    """Closure of a times b by that of b times a, if that has fewer lines of tiles; else nothing.

    Every step but the first half and the last is one of b times a, so the large
    matrix is written once and no closure walks over it.
    """
    outer, inner = a.agg(F.count_distinct("tr"), F.count_distinct("tc")).first()
    if inner >= outer:
        return None
    closed = tile_closure(tile_product(b, a, tile_bits=tile_bits))
    back = checkpointed(tile_sum(b, tile_product(closed, b, tile_bits=tile_bits)))
    return tile_product(a, back, tile_bits=tile_bits, few_inner=True)


def _ones(tiles: DataFrame) -> int:
    return tiles.agg(F.coalesce(F.sum("ones"), F.lit(0))).first()[0]


def _stays_small(tiles: DataFrame) -> bool:
    """Whether a matrix has a square of no more ones than itself, by its witnesses."""
    bits = tiles.agg(F.max(F.size("level_bits"))).first()[0]
    if bits is None:
        return True
    ones = from_tiles(tiles.where("ones > 0"), bits)
    into, out = ones.groupBy(F.col("c").alias("k")).agg(F.count("*").alias("i")), ones.groupBy(F.col("r").alias("k")).agg(F.count("*").alias("o"))
    return into.join(out, "k").agg(F.coalesce(F.sum(F.col("i") * F.col("o")), F.lit(0))).first()[0] <= _ones(tiles)


def tile_reach(tiles: DataFrame, seed: DataFrame, reflexive: bool = False) -> DataFrame:
    """Seed times closure, by rounds of products; the closure is never built.

    Where paths don't branch, as in chains, the step is squared in every round, so
    rounds grow with the logarithm of the longest path; else a round takes a step from
    what is new.
    """
    tiles, seed = checkpointed(tiles), checkpointed(seed)
    seen, step = seed if reflexive else checkpointed(tile_product(seed, tiles)), tiles
    while _stays_small(step):
        # So far all paths of fewer steps than one of ``step`` has.
        more = checkpointed(tile_sum(seen, tile_product(seen, step)))
        if _ones(more) == _ones(seen):
            return seen
        seen, step = more, checkpointed(tile_product(step, step))
        if not _ones(step):
            return seen
    fresh = seen
    while not fresh.isEmpty():
        fresh = checkpointed(tile_sum(tile_product(fresh, step), seen, "diff"))
        if not fresh.isEmpty():
            seen = checkpointed(tile_sum(seen, fresh))
    return seen

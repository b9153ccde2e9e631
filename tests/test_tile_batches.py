"""Tiles that are summed, restricted, numbered and unpacked by batches."""

from __future__ import annotations

import numpy as np
from conftest import SF
from pyspark.sql import functions as F

from pathalgebra.operators import quadtree as qt
from pathalgebra.operators import tiles
from pathalgebra.plans.paths import normalise, parse_path
from pathalgebra.plans.tile_engine import TileEngine, labels_of
from pathalgebra.sources import graphs


def _matrix(spark, cells):
    r, c = np.nonzero(cells)
    return spark.createDataFrame(list(zip(r.tolist(), c.tolist(), strict=True)), "r long, c long")


def _ones(df):
    rows = [(r["r"], r["c"]) for r in df.collect()]
    assert len(rows) == len(set(rows))
    return set(rows)


def _set(cells):
    return set(zip(*(x.tolist() for x in np.nonzero(cells)), strict=True))


def test_keys_of_a_batch_with_empty_and_turned_tiles():
    rng = np.random.default_rng(4)
    cells = [rng.random((8, 8)) < d for d in (0.2, 0.0, 0.7)]
    trees = [qt.encode(*np.nonzero(x), 3).to_bytes() for x in cells]
    keys = tiles._keys(trees, 3, np.array([False, True, True]))
    want = np.concatenate([qt.codes(qt.encode(*np.nonzero(cells[0]), 3)), qt.codes(qt.encode(*np.nonzero(cells[2].T), 3)) + np.uint64(2 << 6)])
    assert (keys == want).all() and not len(tiles._keys([trees[1]], 3))


def test_sums_of_flipped_and_lone_tiles(spark):
    rng = np.random.default_rng(5)
    a, b = rng.random((40, 40)) < 0.1, rng.random((40, 40)) < 0.3
    a[:8, :8] = b[:8, 8:16] = False
    x, y = tiles.to_tiles(_matrix(spark, a), 3), tiles.to_tiles(_matrix(spark, b), 3)
    for left, right, p, q in ((x, y, a, b), (tiles.tile_transpose(x), y, a.T, b), (tiles.tile_transpose(x), tiles.tile_transpose(y), a.T, b.T)):
        for op, want in (("or", p | q), ("and", p & q), ("diff", p & ~q), ("xor", p ^ q)):
            found = tiles.tile_sum(left, right, op)
            assert _ones(tiles.from_tiles(found, 3)) == _set(want)
            line = np.zeros_like(want)
            line[9, 5] = want[9, 5]
            assert _ones(tiles.from_tiles(tiles.tile_sum(left, right, op, 9, 5, 3), 3)) == _set(line)


def test_terms_of_full_and_sparse_tiles(spark):
    cells = np.zeros((70, 70), bool)
    cells[:40, 30:] = True  # full tiles of 32 x 32, and some with few ones
    cells[69, 0] = True
    names = spark.range(70).select((F.col("id") * 7 + 1000).alias("term"), "id")
    packed = tiles.to_tiles(_matrix(spark, cells), 5)
    assert packed.where(F.col("ones") >= tiles._TERMS_ONES).count() and packed.where(F.col("ones") < tiles._TERMS_ONES).count()
    for t, want in ((packed, cells), (tiles.tile_transpose(packed), cells.T)):
        assert _ones(tiles.from_tiles(t, 5, names)) == {(7 * r + 1000, 7 * c + 1000) for r, c in _set(want)}


def test_only_nodes_that_can_answer_are_numbered(spark):
    engine = TileEngine(graphs.commerce(spark, SF))
    engine.matrix(normalise(parse_path("(supp_in/^supp_in)+")))
    supplied = engine.graph.matrix("supp_in")
    assert engine.names.count() == supplied.select("r").union(supplied.select("c")).distinct().count() < engine.graph.nodes().count()
    assert labels_of(parse_path("supp_in?")) is None and labels_of(parse_path("!supp_in")) is None
    # A later path over more labels numbers anew.
    found = _ones(engine.matrix(normalise(parse_path("cust_in/in_region"))))
    assert found == {(r, c) for r, m in _ones(engine.graph.matrix("cust_in")) for n, c in _ones(engine.graph.matrix("in_region")) if m == n}


def test_steps_of_users_are_kept_once(spark):
    g = graphs.activity(spark, SF)
    ends = [g.matrix(x).select(F.col(c).alias("id")) for x in g.labels for c in "rc"]
    every = ends[0]
    for x in ends[1:]:
        every = every.union(x)
    assert {r["id"] for r in g.nodes().collect()} == {r["id"] for r in every.distinct().collect()}
    assert len({r["id"] for r in g.nodes_of(["error"]).collect()}) == g.matrix("error").selectExpr("explode(array(r, c)) id").distinct().count()


def test_a_range_is_closed_on_rows_of_bits():
    rng = np.random.default_rng(6)
    cells = rng.random((128, 128)) < 0.012
    want = cells.copy()
    for k in range(128):
        want |= want[:, k : k + 1] & want[k]
    bands = list(qt.closed_bands(np.sort(qt.interleave(*np.nonzero(cells))), 7, 5))
    assert len(bands) == 4 and (np.concatenate(bands) == want).all()
    assert list(qt.closed_bands(np.array([3], np.uint64), 1, 1))[0].tolist() == [[0, 0], [0, 1]]


def test_ranges_without_a_way_back_are_closed_side_by_side(spark, monkeypatch):
    calls = []
    leaf = tiles._leaf_ranges
    monkeypatch.setattr(tiles, "_LEAF_SIDE", 16)
    monkeypatch.setattr(tiles, "_leaf_ranges", lambda *x: (calls.append(1), leaf(*x))[1])
    cells = np.eye(64, k=1, dtype=bool)
    assert _ones(tiles.from_tiles(tiles.tile_closure(tiles.to_tiles(_matrix(spark, cells), 3)), 3)) == _set(np.triu(np.ones((64, 64), bool), 1))
    assert len(calls) == 1

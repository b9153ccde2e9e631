"""What shows on larger tables only, brought down to small ones."""

from __future__ import annotations

import random

import numpy as np
import pytest
from conftest import SF

from pathalgebra import workloads
from pathalgebra.operators import closure as cl
from pathalgebra.operators import components as comps
from pathalgebra.operators import quadtree as qt
from pathalgebra.operators import tiles


def test_shares_of_a_closure_fit_together_in_any_order_of_edges():
    edges = [(2 * k, 2 * k + 1) for k in range(6000)]  # three blocks of targets
    found = set()
    for share in range(3):
        random.Random(share).shuffle(edges)
        found |= {(v, c) for v, reached in comps.closure_pairs(edges, share, 3) for c in reached}
    assert found == set(edges)


def _pairs(df):
    rows = [(r["r"], r["c"]) for r in df.collect()]
    assert len(rows) == len(set(rows))
    return set(rows)


def _matrix(spark, cells):
    r, c = np.nonzero(cells)
    return spark.createDataFrame(list(zip(r.tolist(), c.tolist(), strict=True)), "r long, c long")


def test_many_trees_at_once():
    rng = np.random.default_rng(1)
    cells = [rng.random((32, 32)) < d for d in (0.01, 0.3, 1.0, 0.05)]
    single = [qt.encode(*np.nonzero(x), 5) for x in cells]
    keys = np.concatenate([qt.codes(t) + np.uint64(i << 10) for i, t in enumerate(single)])
    number, ones, sizes, trees = qt.encode_many(keys, 5)
    assert trees == [t.to_bytes() for t in single] and number.tolist() == [0, 1, 2, 3]
    assert ones.tolist() == [t.ones for t in single] and sizes.tolist() == [t.level_bits for t in single]
    assert (qt.decode_many(trees, 5) == keys).all()
    turned = qt.encode_many(np.sort(qt.turned_keys(keys, 5)), 5)[3]
    assert turned == [qt.turned(t).to_bytes() for t in single]
    for xs, ys in ((trees, trees[:2]), (trees[2:3], trees[1:3])):  # through the quadrants, and as rows of numbers
        found = qt.times_many(xs, ys, 5)
        want = [qt.codes(qt.times(qt.QuadTree.from_bytes(x), qt.QuadTree.from_bytes(y))) + np.uint64((i * len(ys) + j) << 10) for i, x in enumerate(xs) for j, y in enumerate(ys)]
        assert (found == np.concatenate(want)).all()


def test_tiles_are_packed_by_batches(spark):
    rng = np.random.default_rng(2)
    a, b = rng.random((90, 90)) < 0.04, rng.random((90, 90)) < 0.9
    x, y = (tiles.to_tiles(_matrix(spark, v), 3) for v in (a, b))
    assert "FlatMapGroupsInPandas" not in x._jdf.queryExecution().toString()
    as_set = lambda v: set(zip(*(z.tolist() for z in np.nonzero(v)), strict=True))
    times = lambda v, w: (v.astype(int) @ w.astype(int)) > 0
    assert _pairs(tiles.from_tiles(tiles.tile_product(x, y), 3)) == as_set(times(a, b))
    assert _pairs(tiles.from_tiles(tiles.tile_product(tiles.tile_transpose(x), y), 3)) == as_set(times(a.T, b))
    assert _pairs(tiles.from_tiles(tiles.tile_product(x, y, row=3, col=50, tile_bits=3), 3)) == {p for p in as_set(times(a, b)) if p == (3, 50)}


@pytest.mark.parametrize("shape", ["both", "upper", "lower", "apart"])
def test_ranges_of_tiles_are_closed_in_a_task(spark, monkeypatch, shape):
    monkeypatch.setattr(tiles, "_LEAF_SIDE", 16)
    rng = np.random.default_rng(3)
    a = rng.random((60, 60)) < 0.03
    a = {"both": a, "upper": np.triu(a), "lower": np.tril(a), "apart": a & (np.arange(60)[:, None] // 30 == np.arange(60) // 30)}[shape]
    want = a.copy()
    for k in range(60):
        want |= np.outer(want[:, k], want[k])
    got = tiles.tile_closure(tiles.to_tiles(_matrix(spark, a), 2))
    assert _pairs(tiles.from_tiles(got, 2)) == set(zip(*(z.tolist() for z in np.nonzero(want)), strict=True))


@pytest.mark.parametrize("variant", ["left", "right"])
def test_bisection_takes_groups_of_components_together(spark, monkeypatch, variant):
    levels, bisect = [], cl._bisect_groups
    monkeypatch.setattr(cl, "_bisect_groups", lambda *a: levels.append(1) or bisect(*a))
    edges = {(10 * k + i, 10 * k + i + 1) for k in range(40) for i in range(1 + k % 4)} | {(3, 0), (403, 403), (404, 403)}
    want = set(edges)
    while (more := want | {(x, z) for x, y in want for w, z in edges if y == w}) != want:
        want = more
    a = spark.createDataFrame(sorted(edges), "r long, c long")
    assert _pairs(cl.closure(a, "bisect", leaf_ones=12, variant=variant)) == want
    assert len(levels) < 20  # a leaf of 12 ones each would be some 30 of them


def test_leaves_of_many_ones_hold_whole_components(spark, monkeypatch):
    held, leaf = [], cl.leaf_closure
    monkeypatch.setattr(cl, "leaf_closure", lambda a, *more: held.append(a.count()) or leaf(a, *more))
    monkeypatch.setattr(cl, "_GROUP_ONES", 5)
    edges = {(10 * k + i, 10 * k + i + 1) for k in range(40) for i in range(1 + k % 4)} | {(3, 0), (403, 403), (404, 403)}
    large = {(1000 + i, 1000 + (3 * i + 1) % 9) for i in range(9)}  # a component of more ones than a group
    want = edges | large
    while (more := want | {(x, z) for x, y in want for w, z in edges | large if y == w}) != want:
        want = more
    a = spark.createDataFrame(sorted(edges | large), "r long, c long")
    assert _pairs(cl.closure(a, "leaf", leaf_ones=20)) == want
    assert all(x <= 20 for x in held)  # every task held all 108 ones


@pytest.mark.parametrize("name", ["city_example", "grid_source", "udaf_tile_or", "udf_zorder", "udtf_quadrants"])
def test_tasks_read_a_given_table(spark, name):
    df = workloads.queries()[name](spark, SF)
    assert any(x.endswith(("/lineitem.parquet", "/events.parquet")) or "/lineitem.parquet/" in x for x in df.inputFiles())
    assert df.count() > 5

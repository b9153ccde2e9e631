"""Walks over chains on tiles, and products of many sparse tiles at once."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pytest

from pathalgebra.operators import quadtree as qt
from pathalgebra.operators import tiles


def _matrix(spark, cells):
    return spark.createDataFrame(sorted(cells), "r long, c long")


def _ones(df):
    rows = [(r["r"], r["c"]) for r in df.collect()]
    assert len(rows) == len(set(rows))
    return set(rows)


def _reached(edges, seed, reflexive):
    found = set(seed) if reflexive else set()
    fresh = {(r, c) for r, k in seed for x, c in edges if x == k}
    while fresh - found:
        found |= fresh
        fresh = {(r, c) for r, k in fresh for x, c in edges if x == k}
    return found


CHAIN = {(k, k + 1) for k in range(64)} | {(70, 71), (71, 70)}
GRAPHS = {"chain": CHAIN, "tree": {((k + 1) // 2 - 1, k) for k in range(1, 31)}, "branches": {(k, (7 * k + j) % 40) for k in range(40) for j in (1, 5)}}


@pytest.mark.parametrize("reflexive", [False, True])
@pytest.mark.parametrize("name", GRAPHS)
def test_reach(spark, name, reflexive):
    edges, seed = GRAPHS[name], {(3, 0), (5, 30), (6, 70), (7, 99)}
    found = tiles.tile_reach(tiles.to_tiles(_matrix(spark, edges), 3), tiles.to_tiles(_matrix(spark, seed), 3), reflexive)
    assert _ones(tiles.from_tiles(found, 3)) == _reached(edges, seed, reflexive)


def test_rounds_of_a_chain_are_few(spark, monkeypatch):
    products, product = [], tiles.tile_product
    monkeypatch.setattr(tiles, "tile_product", lambda *a, **o: products.append(1) or product(*a, **o))
    seed = {(0, 0)}
    found = tiles.tile_reach(tiles.to_tiles(_matrix(spark, CHAIN), 3), tiles.to_tiles(_matrix(spark, seed), 3))
    assert _ones(tiles.from_tiles(found, 3)) == _reached(CHAIN, seed, False)
    assert len(products) < 20  # a round for each step would be 65 of them


def test_strips_of_few_witnesses_are_multiplied_together(spark, monkeypatch):
    def alone(*args, **options):
        raise AssertionError("a pair of sparse strips went by itself")

    rng = np.random.default_rng(8)
    a, b = rng.random((60, 60)) < 0.05, rng.random((60, 60)) < 0.05
    x, y = (tiles.to_tiles(_matrix(spark, set(zip(*(z.tolist() for z in np.nonzero(v)), strict=True))), 3) for v in (a, b))
    for left, p in ((x, a), (tiles.tile_transpose(x), a.T)):
        want = set(zip(*(z.tolist() for z in np.nonzero((p.astype(int) @ b.astype(int)) > 0)), strict=True))
        assert _ones(tiles.from_tiles(tiles.tile_product(left, y), 3)) == want
    strip = x.toPandas()
    pairs = {"x": [strip["tr"].tolist()], "x_bits": [strip["bits"].tolist()], "x_flipped": [strip["flipped"].tolist()], "y": [strip["tc"].tolist()], "y_bits": [strip["bits"].tolist()], "y_flipped": [strip["flipped"].tolist()]}
    monkeypatch.setattr(qt, "times_many", alone)
    assert len(list(tiles._multiplied(pd.DataFrame(pairs)))) == 1
    monkeypatch.setattr(tiles, "_FEW_WITNESSES", 1)
    assert list(tiles._multiplied(pd.DataFrame(pairs))) == []  # left for times_many

"""Closures on tiles whose components make many pairs are expanded by blocks."""

from __future__ import annotations

import pytest

from pathalgebra.operators import components as comps
from pathalgebra.operators import tiles
from pathalgebra.plans.evaluate import answer
from pathalgebra.sources.graphs import Graph

#: Two rings, one leading to the other, and a tail.
EDGES = {(k, (k + 1) % 40) for k in range(40)} | {(k, (k + 9) % 40) for k in range(40)} | {(50 + k, 50 + (k + 1) % 20) for k in range(20)} | {(50 + k, 50 + (k + 3) % 20) for k in range(20)} | {(7, 55), (60, 80), (80, 81), (0, 20), (50, 58)}
RINGS, SMALL = set(range(40)), set(range(50, 70))
WANT = {(r, c) for r in RINGS for c in RINGS | SMALL | {80, 81}} | {(r, c) for r in SMALL for c in SMALL | {80, 81}} | {(80, 81)}


@pytest.mark.parametrize("leaf_ones", [200_000, 50])
def test_saturated_closures_dont_multiply_tiles(spark, monkeypatch, leaf_ones):
    def product(*args, **options):
        raise AssertionError("tiles were closed")

    monkeypatch.setattr(comps, "_MOST_PAIRS", 1000)
    monkeypatch.setattr(comps.saturated, "__defaults__", (leaf_ones,))
    monkeypatch.setattr(tiles, "tile_closure", product)
    a = spark.createDataFrame(sorted(EDGES), "r long, c long")
    rows = [(r["r"], r["c"]) for r in tiles.closed_pairs(tiles.to_tiles(a, 3), 3).collect()]
    assert len(rows) == len(set(rows)) and set(rows) == WANT


def test_other_closures_stay_on_tiles(spark, monkeypatch):
    closed, close = [], tiles.tile_closure
    monkeypatch.setattr(tiles, "tile_closure", lambda x: closed.append(1) or close(x))
    a = spark.createDataFrame(sorted(EDGES), "r long, c long")
    rows = {(r["r"], r["c"]) for r in tiles.closed_pairs(tiles.to_tiles(a, 3), 3).collect()}
    assert rows == WANT and closed


def test_saturated_paths_dont_multiply_tiles(spark, monkeypatch):
    def product(*args, **options):
        raise AssertionError("tiles were closed")

    monkeypatch.setattr(comps, "_MOST_PAIRS", 1000)
    monkeypatch.setattr(tiles, "tile_closure", product)
    graph = Graph.from_triples(spark.createDataFrame([(r + 500, "a", c + 500) for r, c in EDGES], "s long, p string, o long"))
    rows = [(r["x"] - 500, r["y"] - 500) for r in answer(graph, "?x a+ ?y", engine="tiles", tile_bits=3).collect()]
    assert len(rows) == len(set(rows)) and set(rows) == WANT

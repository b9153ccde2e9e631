"""Closures of paths there and back on tiles, products of few inner lines, and unpacking by many tasks."""

from __future__ import annotations

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from pathalgebra.operators import quadtree as qt
from pathalgebra.operators import tiles
from pathalgebra.plans.evaluate import answer
from pathalgebra.sources.graphs import Graph


@pytest.mark.parametrize("cells, unfolded", [(1 << 25, 1 << 22), (1 << 13, 100)])
def test_products_joined_on_the_inner_line(monkeypatch, cells, unfolded):
    rng = np.random.default_rng(4)
    xs, ys = ([qt.encode(*np.nonzero(rng.random((64, 64)) < d), 6).to_bytes() for d in ds] for ds in ((0.01, 0.3), (0.02, 0.2, 0.05)))
    x, y = qt.decode_many(xs, 6), qt.decode_many(ys, 6)
    monkeypatch.setattr(qt, "_CELLS", cells)
    monkeypatch.setattr(qt, "_UNFOLDED", unfolded)
    assert (qt._joined(x, y, 6, 2, 3) == qt.times_many(xs, ys, 6)).all()


@pytest.mark.parametrize("path", ["(a/^a)+", "(a/^a)*", "(a/b)+", "(a/b/c)+", "(^a/a)+"])
def test_round_trips(spark, path):
    draw = random.Random(5)
    rows = [(draw.randrange(100, 140), "a", draw.randrange(4)) for _ in range(50)] + [(draw.randrange(4), "b", draw.randrange(100, 140)) for _ in range(6)]
    rows += [(draw.randrange(100, 140), "c", draw.randrange(100, 140)) for _ in range(30)]
    graph = Graph.from_triples(spark.createDataFrame(rows, "s long, p string, o long"))
    query = f"?x {path} ?y"
    found = [(r["x"], r["y"]) for r in answer(graph, query, engine="tiles", tile_bits=2).collect()]
    assert len(found) == len(set(found)) and set(found) == {(r["x"], r["y"]) for r in answer(graph, query).collect()}


def test_the_smaller_round_trip_is_closed(spark, monkeypatch):
    graph = Graph.from_triples(spark.createDataFrame([(100 + k, "a", k % 3) for k in range(60)], "s long, p string, o long"))
    closed, close = [], tiles.tile_closure
    monkeypatch.setattr(tiles, "tile_closure", lambda x: closed.append(x) or close(x))
    assert answer(graph, "?x (a/^a)+ ?y", engine="tiles", tile_bits=2).count() == 1200
    assert [x.count() for x in closed] == [1]


def test_full_tiles_are_unpacked_by_many_tasks(spark):
    side = spark.range(160)
    a = side.select(F.col("id").alias("r")).crossJoin(side.select(F.col("id").alias("c")))
    out = tiles.from_tiles(tiles.to_tiles(a, 5), 5, side.select((F.col("id") + 7).alias("term"), "id"))
    assert out.distinct().count() == 160 * 160
    assert out.select(F.spark_partition_id().alias("p")).distinct().count() > 4

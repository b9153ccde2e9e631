"""Chains from a constant on tiles: only what the constant reaches is numbered."""

from __future__ import annotations

import random

import pytest

from pathalgebra.plans import tile_engine
from pathalgebra.plans.evaluate import answer
from pathalgebra.plans.paths import node
from pathalgebra.sources.graphs import Graph


@pytest.fixture(scope="module")
def graph(spark):
    draw = random.Random(6)
    rows = [(draw.randrange(300), p, draw.randrange(300)) for p in "ab" for _ in range(400)] + [(1, "a", 2), (2, "b", 3), (3, "a", 1)]
    rows = [(node("user", s), p, node("user", o)) for s, p, o in rows]
    return Graph.from_triples(spark.createDataFrame(rows, "s long, p string, o long"))


@pytest.mark.parametrize("query", ["user:1 a/b/a ?y", "?x a/^b/b user:3", "user:1 a/b user:3", "user:1 (a|b)/^a/(a|^b) ?y", "user:999 a/b ?y", "user:1 a/c ?y"])
def test_chains_from_a_constant(graph, query):
    found, want = ([(r["x"], r["y"]) for r in answer(graph, query, **how).collect()] for how in ({"engine": "tiles", "tile_bits": 4}, {}))
    assert sorted(found) == sorted(want)


def test_only_reached_nodes_are_numbered(graph, monkeypatch):
    numbered, number = [], tile_engine.dense_numbers
    monkeypatch.setattr(tile_engine, "dense_numbers", lambda terms, column: numbered.append(number(terms, column)) or numbered[-1])
    assert not answer(graph, "user:1 a/b ?y", engine="tiles", tile_bits=4).isEmpty()
    assert [x.count() < 30 for x in numbered] == [True]

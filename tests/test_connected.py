"""The automaton over moves that can be undone: nothing is walked from each origin."""

from __future__ import annotations

import random

import pytest

from pathalgebra.plans import automaton
from pathalgebra.plans.evaluate import answer
from pathalgebra.sources.graphs import Graph


def _rows(df, *names):
    rows = [tuple(r[k] for k in names) for r in df.collect()]
    assert len(rows) == len(set(rows))
    return set(rows)


def _triples(spark, rows):
    return Graph.from_triples(spark.createDataFrame(rows, "s long, p string, o long"))


@pytest.fixture(scope="module")
def tangle(spark):
    draw = random.Random(3)
    rows = [(draw.randrange(30), "a", 100 + draw.randrange(30)) for _ in range(35)]
    rows += [(draw.randrange(30), "b", draw.randrange(30)) for _ in range(20)] + [(draw.randrange(30), "c", 200 + draw.randrange(8)) for _ in range(20)]
    return _triples(spark, rows)


@pytest.mark.parametrize("path", ["(a/^a)+", "(a/^a)*", "(a/^a|b)+", "b/(a/^a)+", "((a/^a)+/b)+", "(a/^a/c/^c)+", "(c/^c|a/^a)+/c", "(^a/a)*"])
def test_walk_over_connected_places(spark, tangle, path):
    query = f"?x {path} ?y"
    assert _rows(answer(tangle, query, engine="automaton"), "x", "y") == _rows(answer(tangle, query, engine="joins"), "x", "y")


def test_walk_keeps_less_than_its_pairs(spark, monkeypatch):
    graph = _triples(spark, [(k, "a", 10_000 + k // 200) for k in range(400)] + [(0, "a", 10_001)])
    kept = []
    keep = automaton.checkpointed
    monkeypatch.setattr(automaton, "checkpointed", lambda df: kept.append(keep(df)) or kept[-1])
    assert answer(graph, "?x (a/^a)+ ?y", engine="automaton").count() == 160_000
    assert max(x.count() for x in kept) < 2000

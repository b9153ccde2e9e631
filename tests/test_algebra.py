"""Laws, worked examples, and engines against brute force on small graphs."""

from __future__ import annotations

import random

import pytest

from pathalgebra.operators import closure as cl
from pathalgebra.operators import components as comps
from pathalgebra.operators import matrix as m
from pathalgebra.operators import tiles
from pathalgebra.plans.evaluate import answer
from pathalgebra.plans.paths import parse_path
from pathalgebra.sources.graphs import Graph, city
from pathalgebra.streaming.edges import add_edges


def frame(spark, pairs):
    return spark.createDataFrame(sorted(pairs), "r long, c long")


def pairs(df):
    rows = [(r["r"], r["c"]) for r in df.collect()]
    assert len(rows) == len(set(rows))
    return set(rows)


def times(a, b):
    return {(x, z) for x, y in a for w, z in b if y == w}


def plus(a):
    out = set(a)
    while True:
        new = out | times(out, a)
        if new == out:
            return out
        out = new


def draw(seed, n=12, ones=18):
    rng = random.Random(seed)
    return {(rng.randrange(n), rng.randrange(n)) for _ in range(ones)}


def test_city_example(spark):
    g = city(spark)
    e = parse_path("walk/(orange|red)+/walk")
    assert e is not None
    got = {(r["x"], r["y"]) for r in answer(g, "?x walk/(orange|red)+/walk ?y").collect()}
    assert {y for x, y in got if x == 6} == {6, 7, 8}
    assert len(got) == 9
    assert answer(g, "?x (orange|red)+ ?y").count() == 16


def test_set_laws(spark):
    a, b = draw(1), draw(2)
    x, y = frame(spark, a), frame(spark, b)
    assert pairs(m.union(x, y)) == a | b
    assert pairs(m.intersect(x, y)) == a & b == pairs(m.minus(x, m.minus(x, y)))
    assert pairs(m.xor(x, y)) == a ^ b == pairs(m.xor_outer(x, y))
    assert pairs(m.union(x, y, row=3)) == {p for p in a | b if p[0] == 3}


@pytest.mark.parametrize("method", ["outer", "rowwise", "salted"])
def test_products(spark, method):
    a, b = draw(3), draw(4)
    x, y = frame(spark, a), frame(spark, b)
    assert pairs(m.product(x, y, method=method)) == times(a, b)
    assert pairs(m.product(x, y, row=2, col=5, method=method)) == {p for p in times(a, b) if p == (2, 5)}


def test_outer_product_example(spark):
    a = {(1, 5), (2, 2), (6, 2), (7, 2), (7, 7), (8, 7), (7, 8), (8, 8)}
    b = {(2, 6), (2, 7), (5, 1), (5, 4), (7, 7), (7, 8), (8, 1), (8, 4), (8, 7), (8, 8)}
    want = {1: {1, 4}, 2: {6, 7}, 6: {6, 7}, 7: {1, 4, 6, 7, 8}, 8: {1, 4, 7, 8}}
    assert pairs(m.product(frame(spark, a), frame(spark, b))) == {(r, c) for r, cs in want.items() for c in cs}


@pytest.mark.parametrize(("method", "options"), [("squaring", {}), ("linear", {}), ("leaf", {}), ("components", {}), ("components", {"leaf_ones": 3}), ("bisect", {"leaf_ones": 4}), ("bisect", {"leaf_ones": 4, "variant": "right"})])
def test_closures_agree(spark, method, options):
    a = draw(5)
    assert pairs(cl.closure(frame(spark, a), method, **options)) == plus(a)


@pytest.mark.parametrize("leaf", [1000, 0])
def test_restricted_and_seeded_closures(spark, leaf):
    a, seed = draw(6), {(100, 1), (101, 2)}
    x, s = frame(spark, a), frame(spark, seed)
    full = plus(a)
    assert pairs(cl.closure_from(x, 1, leaf_ones=leaf)) == {p for p in full if p[0] == 1}
    assert pairs(cl.closure_to(x, 1, leaf_ones=leaf)) == {p for p in full if p[1] == 1}
    assert pairs(cl.closure_apply(x, s, leaf_ones=leaf)) == times(seed, full)
    assert pairs(cl.closure_apply(x, s, reflexive=True, leaf_ones=leaf)) == seed | times(seed, full)
    assert pairs(cl.reachable(x, 1, 2, leaf_ones=leaf)) == full & {(1, 2)}


def test_restricting_a_closure_operand_is_no_law(spark):
    a = {(1, 2), (2, 3)}
    assert pairs(m.restrict(cl.closure(frame(spark, a)), row=1)) == {(1, 2), (1, 3)} != plus({(1, 2)})


@pytest.mark.parametrize("leaf", [1000, 0])
def test_components_and_count(spark, leaf):
    a = {(1, 2), (2, 1), (2, 3), (3, 4), (4, 5), (5, 3), (6, 6), (7, 8)}
    x = frame(spark, a)
    got = {r["id"]: r["comp"] for r in comps.components(x, leaf).collect()}
    assert got == {1: 1, 2: 1, 3: 3, 4: 3, 5: 3, 6: 6, 7: 7, 8: 8}
    factored = comps.factored_closure(x)
    assert factored.count_pairs() == len(plus(a)) and pairs(factored.pairs()) == plus(a)


def test_tiles(spark):
    a, b = {(r * 7, c * 5) for r, c in draw(7)}, {(r * 5, c * 7) for r, c in draw(8)}
    x, y = tiles.to_tiles(frame(spark, a), 4), tiles.to_tiles(frame(spark, b), 4)
    assert pairs(tiles.from_tiles(x, 4)) == a
    assert pairs(tiles.from_tiles(tiles.tile_transpose(x), 4)) == {(c, r) for r, c in a}
    for op, want in (("or", a | b), ("and", a & b), ("diff", a - b), ("xor", a ^ b)):
        assert pairs(tiles.from_tiles(tiles.tile_sum(x, y, op), 4)) == want
    assert pairs(tiles.from_tiles(tiles.tile_product(x, y), 4)) == times(a, b)


QUERIES = ["?x a/b ?y", "?x (a|b)+ ?y", "node a*/b ?y", "?x a?/b* node", "?x ^a/b+ ?y", "node (a/b)+ node", "?x a+ ?x", "?x !(a) ?y", "?x () ?y", "?x c ?y", "?x (a|^b)*/b?/a ?y"]


@pytest.mark.parametrize("text", QUERIES)
def test_engines_agree(spark, text):
    rows = [(r, "a", c) for r, c in draw(9, 8, 9)] + [(r, "b", c) for r, c in draw(10, 8, 9)]
    g = Graph.from_triples(spark.createDataFrame([*rows, rows[0], (None, "a", 1)], "s long, p string, o long"))
    text = text.replace("node", "index:0")
    from pathalgebra.plans import paths

    shift = paths.node("index", 0)
    g = Graph.from_triples(g.triples().selectExpr(f"s + {shift} as s", "p", f"o + {shift} as o"))
    results = [{(r["x"], r["y"]) for r in answer(g, text, **o).collect()} for o in ({}, {"plan": "naive"}, {"engine": "joins"}, {"engine": "automaton"}, {"leaf_ones": 0})]
    assert all(r == results[0] for r in results)


def test_new_edges_on_a_closure(spark):
    base, fresh = {(1, 2), (3, 4)}, {(2, 3), (4, 1)}
    got = add_edges(frame(spark, plus(base)), frame(spark, base), frame(spark, fresh))
    assert pairs(got) == plus(base | fresh)


def test_restricted_end_reaches_the_scan(spark, tmp_path):
    path = str(tmp_path / "m")
    frame(spark, draw(11)).write.parquet(path)
    plan = m.product(spark.read.parquet(path), spark.read.parquet(path), row=3)._jdf.queryExecution().toString()
    assert "EqualTo(r,3)" in plan

"""What the planner decides, seen in its notes, and closures that stay bounded."""

from __future__ import annotations

import itertools
import tracemalloc

import pytest

from pathalgebra.operators import closure as cl
from pathalgebra.operators.components import closure_pairs
from pathalgebra.plans.evaluate import Engine, answer, count_pairs, explain, mirrored, targets
from pathalgebra.plans.paths import normalise, parse_path, text_of
from pathalgebra.sources import graphs
from pathalgebra.sources.store import DualGraph, drop_dual

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def chain_graph(spark):
    edges = {"w": [(10, 1), (11, 3), (12, 1), (13, 13), (4, 14), (5, 15), (5, 16), (17, 17)], "s": [(1, 2), (3, 2)], "n": [(2, 4), (2, 5), (9, 9)]}
    return graphs.Graph.from_triples(spark.createDataFrame([(a, p, b) for p, v in edges.items() for a, b in v], "s long, p string, o long"))


def rows(df):
    return {tuple(r) for r in df.collect()}


def test_products_go_by_size(chain_graph):
    worker = Engine(chain_graph)
    got = rows(worker.matrix(normalise(parse_path("w/s/n/w"))))
    assert got == rows(Engine(chain_graph, "naive").matrix(normalise(parse_path("w/s/n/w")))) and len(got) == 9
    # The small pair first; then both neighbours tie, and the left one is taken.
    assert [x for x in worker.notes if x.startswith("multiply")] == ["multiply 1 and 2: 4 ones", "multiply 0 and 4: 6 ones", "multiply 5 and 3: 9 ones"]


def test_closures_join_the_smaller_neighbour(chain_graph):
    for path in ("w/n*/s", "s/n+/w", "w/s?/n*/w", "n*/s*"):
        e = normalise(parse_path(path))
        assert rows(Engine(chain_graph).matrix(e)) == rows(Engine(chain_graph, "naive").matrix(e)), path


def test_sums_by_size(chain_graph):
    worker = Engine(chain_graph, sums="by_size")
    e = normalise(parse_path("w|s|n"))
    assert rows(worker.matrix(e)) == rows(Engine(chain_graph).matrix(e))
    assert [x for x in worker.notes if x.startswith("add")] == ["add 1 and 2: 5 ones", "add 3 and 0: 13 ones"]


def test_the_emptier_end_is_the_start(chain_graph):
    for row, col in ((10, 14), (13, 17), (12, 16)):
        worker = Engine(chain_graph)
        e = normalise(parse_path("w/s/n/w"))
        want = {p for p in rows(Engine(chain_graph, "naive").matrix(e)) if p == (row, col)}
        assert rows(worker.matrix(e, row, col)) == want
        assert any(x.startswith("ends:") for x in worker.notes)


def test_paths_there_and_back(spark):
    g = graphs.weblinks(spark, SF)
    assert text_of(mirrored(normalise(parse_path("links_to/^links_to")))) == "links_to"
    assert mirrored(normalise(parse_path("links_to/^on_host"))) is None
    assert mirrored(normalise(parse_path("^a/b/^b/a"))) is not None
    worker = Engine(g)
    got = rows(worker.matrix(normalise(parse_path("(links_to/^links_to)+"))))
    assert got == rows(Engine(g, "naive").matrix(normalise(parse_path("(links_to/^links_to)+"))))
    assert any("undirected" in x for x in worker.notes)
    assert got == rows(Engine(g, leaf_ones=0).matrix(normalise(parse_path("(links_to/^links_to)+"))))
    assert count_pairs(g, "?x (links_to/^links_to)+ ?y") == len(got)


def test_factors_are_walked(spark):
    g = graphs.commerce(spark, SF)
    text = "customer:7 (^placed_by/contains/^contains/placed_by)+ ?y"
    assert rows(answer(g, text)) == rows(answer(g, text, leaf_ones=0))
    assert targets(g, text).count() == answer(g, text).count()


def test_dual_views_serve_a_chain(spark):
    dual = DualGraph.write(graphs.geography(spark, SF), buckets=4)
    try:
        found = Engine(dual).matrix(normalise(parse_path("in_region/^in_region")))
        assert found.count() == 125
        assert found._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning") == 1  # that of the final distinct
    finally:
        drop_dual(spark, dual.name)


def test_explain_shows_sizes(chain_graph):
    text = explain(chain_graph, "?x w/s/n/w ?y")
    assert "sizes w: 8, s: 2, n: 3, w: 8" in text and "cost" in text and "Physical Plan" in text


def test_a_long_chain_stays_small():
    edges = [(i, i + 1) for i in range(200_000)]
    tracemalloc.start()
    first = list(itertools.islice(closure_pairs(edges), 3))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert all(v < min(found) for v, found in first) and peak < 600_000_000


def test_shares_together_are_the_closure():
    edges = [(i, (i * 7 + 3) % 9000) for i in range(0, 9000, 2)]
    whole = {(v, c) for v, found in closure_pairs(edges) for c in found}
    parts = [{(v, c) for v, found in closure_pairs(edges, k, 3) for c in found} for k in range(3)]
    assert set().union(*parts) == whole and sum(map(len, parts)) == len(whole)


def test_rounds_stop_at_a_cell(spark):
    a = spark.createDataFrame([(i, i + 1) for i in range(12)], "r long, c long")
    assert rows(cl.reachable(a, 2, 5, leaf_ones=0)) == {(2, 5)} and not rows(cl.reachable(a, 5, 2, leaf_ones=0))
    assert rows(cl.reachable(a, 3, 3, reflexive=True)) == {(3, 3)}

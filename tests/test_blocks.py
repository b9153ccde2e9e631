"""Large components are expanded by blocks, and paths there and back aren't built."""

from __future__ import annotations

from conftest import SF, same_rows

from pathalgebra import workloads
from pathalgebra.operators import closure as cl
from pathalgebra.operators import components as comps


def _rows(df, *names):
    rows = [tuple(r[k] for k in names) for r in df.collect()]
    assert len(rows) == len(set(rows))
    return set(rows)


def test_blocks_of_members_meet_once(spark):
    comp = [(v, 0) for v in range(1300)] + [(5000 + v, 5000) for v in range(3)] + [(6000, 6000)]
    closure = comps.FactoredClosure(spark.createDataFrame(comp, "id long, comp long"), spark.createDataFrame([(5000, 0), (6000, 5000), (6000, 0)], "r long, c long"), spark.createDataFrame([(0,), (5000,)], "comp long"))
    large, small = set(range(1300)), {5000, 5001, 5002}
    want = {(r, c) for r in large | small | {6000} for c in large} | {(r, c) for r in small | {6000} for c in small}
    assert _rows(closure.pairs(), "r", "c") == want


def test_component_expand_builds_no_path_there_and_back(spark, duck, monkeypatch):
    def product(*args, **options):
        raise AssertionError("the product was built")

    monkeypatch.setattr("pathalgebra.operators.matrix.product", product)
    same_rows(workloads.component_expand(spark, SF), duck, workloads.oracle_sql()["component_expand"])


def test_pairs_of_one_component_come_from_many_tasks(spark):
    comp = spark.range(2000).selectExpr("id", "cast(0 as bigint) AS comp")
    closure = comps.FactoredClosure(comp, spark.createDataFrame([], "r long, c long"), spark.createDataFrame([(0,)], "comp long"))
    by_task = closure.pairs().selectExpr("spark_partition_id() AS p").groupBy("p").count().collect()
    assert sum(x["count"] for x in by_task) == 4_000_000 and len(by_task) > 4


def test_few_ones_of_many_pairs_are_expanded_by_blocks(spark, monkeypatch):
    monkeypatch.setattr(comps, "_MOST_PAIRS", 100_000, raising=False)
    cycle = [(v, (v + 1) % 600) for v in range(600)]
    edges = [*cycle, (1000, 0), (599, 2000), (2000, 2001), (3000, 3001), (3001, 3000), (4000, 4000)]
    a = spark.createDataFrame(edges, "r long, c long")
    found = cl.closure(a)
    assert "explode(c" in found._jdf.queryExecution().executedPlan().toString()
    assert _rows(found, "r", "c") == {(r, c) for r, reached in comps.closure_pairs(edges) for c in reached}
    chain = cl.closure(spark.createDataFrame([(v, v + 1) for v in range(600)], "r long, c long"))
    assert chain.count() == 600 * 601 // 2


def test_a_task_never_holds_the_product_of_two_blocks(spark):
    side = spark.range(3000).selectExpr("id % 2 AS key", "id")
    pairs = comps.expanded(side.withColumnRenamed("id", "r"), side.withColumnRenamed("id", "c"))
    plan = pairs._jdf.queryExecution().executedPlan().toString()
    # A narrow step that isn't generated code lies between the two sides.
    assert plan.index("explode(c") < plan.index("Coalesce") < plan.index("explode(r")
    assert pairs.count() == pairs.distinct().count() == 2 * 1500 * 1500

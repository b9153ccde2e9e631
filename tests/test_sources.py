from __future__ import annotations

from pathalgebra.experiments import query_log, space
from pathalgebra.functions import udfs
from pathalgebra.functions.measures import alternation, latency_table
from pathalgebra.sources import graphs, io, store

SF = "/root/testdata/sf0.001"


def test_ntriples_and_numbers(spark, tmp_path):
    (tmp_path / "g.nt").write_text('<b> <p> <a> .\n<a> <p> "x y"@en .\nbroken\n<b> <p> <a> .\n')
    triples = io.read_triples(spark, str(tmp_path / "g.nt"), "ntriples")
    assert triples.count() == 2
    numbered, names = io.encode_triples(triples)
    assert {r.term: r.id for r in names.collect()} == {'"x y"@en': 0, "<a>": 1, "<b>": 2}
    assert {(r.s, r.o) for r in numbered.collect()} == {(2, 1), (1, 0)}


def test_dual_views_join_without_exchange(spark):
    triples = graphs.commerce(spark, SF).triples().where("p in ('placed_by', 'cust_in')")
    store.write_dual(triples, "dual_test", 4)
    try:
        product = store.dual_product(spark, "dual_test", "placed_by", "cust_in")
        assert product.count() == 1500
        plan = product._jdf.queryExecution().executedPlan().toString()
        assert plan.count("Exchange hashpartitioning") == 1  # that of the final distinct
    finally:
        for t in ("dual_test_by_s", "dual_test_by_o"):
            spark.sql(f"DROP TABLE IF EXISTS {t}")


def test_uniform_counts(spark):
    assert graphs.uniform(spark, 1e-2, 3).count() == 10_153
    assert graphs.uniform(spark, 1e-3, 7).count() == 1_019


def test_alternation_of_clusters(spark):
    a = spark.createDataFrame([(r, c) for r in range(4) for c in range(4)], "r long, c long")
    b = spark.createDataFrame([(r + 8, c) for r in range(4) for c in range(4)], "r long, c long")
    assert alternation(a, b) == 1 and alternation(a, b, "switches") == 1
    assert alternation(a, a) == 16 and alternation(a, a, "switches") == 0


def test_sql_surface(spark):
    udfs.register(spark)
    rows = spark.sql("SELECT path_is_valid(p) AS ok FROM VALUES ('a/b+'), ('a/'), (NULL) AS t(p)").collect()
    assert [r.ok for r in rows] == [True, False, False]
    assert [r.token for r in spark.sql("SELECT token FROM path_tokens('a/(b|c)+')").collect()] == ["a", "/", "(", "b", "|", "c", ")", "+"]
    udfs.create_path_view(spark, "mates", graphs.geography(spark, SF), "?x in_region/^in_region ?y")
    assert spark.sql("SELECT count(*) AS n FROM mates").first().n == 125


def test_log_and_space(spark):
    log = query_log(spark, SF, ["rpq_concat_vv", "rpq_chain_vc"])
    assert log.count() == 6 and not log.where("timed_out").count()
    assert latency_table(log).count() == 9
    sizes = space(spark, SF)
    assert sizes["raw_pairs"] == 8 and sizes["tiles"]["bytes"] > 0

"""Queries around the engine: patterns, views, sketches, functions of users, a data source, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pathalgebra.functions import udfs
from pathalgebra.functions.measures import label_stats as stats_of
from pathalgebra.operators import quadtree as qt
from pathalgebra.operators import tiles
from pathalgebra.plans.evaluate import count_pairs, targets
from pathalgebra.plans.to_sql import MATRICES, query_sql
from pathalgebra.runtime import table
from pathalgebra.sources import graphs

Query = Callable[[SparkSession, str], DataFrame]


def edges_all(spark, sf):
    return graphs.geography(spark, sf).triples()


def label_stats(spark, sf):
    return stats_of(graphs.commerce(spark, sf).triples())


def web_links(spark, sf):
    """Links of each page by the first part of their address."""
    pages = table(spark, sf, "pages")
    links = pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("href"))
    return links.groupBy("page_id").agg(F.count("*").alias("links"), F.countDistinct("href").alias("addresses"), F.count_if(F.substring("href", 1, 1) == "/").alias("inside"))


def pattern_star_join(spark, sf):
    """Orders with a part of a brand, a supplier and a customer of one nation: three edges from one node."""
    g = graphs.commerce(spark, sf)
    bought = g.matrix("placed_by").select(F.col("r").alias("order"), F.col("c").alias("customer"))
    sent = g.matrix("shipped_from").select(F.col("r").alias("order"), F.col("c").alias("supplier"))
    homes = g.matrix("cust_in").select(F.col("r").alias("customer"), F.col("c").alias("nation"))
    yards = g.matrix("supp_in").select(F.col("r").alias("supplier"), F.col("c").alias("nation"))
    return bought.join(homes, "customer").join(sent.join(yards, "supplier"), ["order", "nation"]).select("order", "customer", "supplier", "nation")


def _star_sql() -> str:
    x = MATRICES["commerce"]
    return (
        f'SELECT b.r AS "order", b.c AS customer, s.c AS supplier, h.c AS nation FROM ({x["placed_by"]}) AS b JOIN ({x["cust_in"]}) AS h ON b.c = h.r '
        f'JOIN ({x["shipped_from"]}) AS s ON s.r = b.r JOIN ({x["supp_in"]}) AS y ON y.r = s.c AND y.c = h.c'
    )


def degree_grouping_sets(spark, sf):
    table(spark, sf, "lineitem").createOrReplaceTempView("degree_lines")
    return spark.sql(
        "SELECT coalesce(l_returnflag, 'all') AS flag, coalesce(l_linestatus, 'all') AS status, count(*) AS n FROM degree_lines "
        "GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())"
    )


def rows_intersect(spark, sf):
    """Nodes that two labels reach from the same user, as arrays."""
    g = graphs.activity(spark, sf)
    left, right = (g.matrix(p).groupBy("r").agg(F.collect_set("c").alias(p)) for p in ("click", "view"))
    both = left.join(right, "r").select("r", F.array_sort(F.array_intersect("click", "view")).alias("both"))
    return both.select("r", F.size("both").cast("long").alias("n"), F.array_join("both", ",").alias("shared"))


def cast_ids(spark, sf):
    """Keys as text and back; what isn't a number becomes null."""
    rows = table(spark, sf, "part").select("p_partkey", F.expr("try_cast(p_brand AS bigint)").alias("brand"), F.expr("try_cast(cast(p_partkey AS string) AS int)").alias("key"))
    return rows.select("p_partkey", "brand", F.col("key").cast("long").alias("key"), F.col("p_partkey").cast("decimal(20,0)").cast("string").alias("text"))


def pair_struct(spark, sf):
    rows = graphs.geography(spark, sf).matrix("in_region").select(F.struct(F.col("r").alias("x"), F.col("c").alias("y")).alias("pair"))
    return rows.select(F.col("pair").withField("y", F.col("pair.y") + 1).alias("pair")).select("pair.x", "pair.y")


def approx_nodes(spark, sf):
    """Ends of each label by a mergeable sketch, in per cent of the true number, rounded to tens: 100 where the sketch is good."""
    edges = graphs.commerce(spark, sf).triples()
    per = edges.groupBy("p").agg(F.hll_sketch_estimate(F.hll_sketch_agg("s", F.lit(14))).alias("about"), F.countDistinct("s").alias("n"))
    return per.select("p", F.expr("cast(round(10.0 * about / n) * 10 as bigint)").alias("percent"))


def bitmap_rows(spark, sf):
    """Distinct customers by nation, counted by bitmaps that merge bucket by bucket."""
    rows = table(spark, sf, "customer").select("c_nationkey", F.bitmap_bucket_number("c_custkey").alias("bucket"), F.bitmap_bit_position("c_custkey").alias("bit"))
    maps = rows.groupBy("c_nationkey", "bucket").agg(F.bitmap_count(F.bitmap_construct_agg("bit")).alias("n"))
    return maps.groupBy("c_nationkey").agg(F.sum("n").alias("n"))


def top_neighbors_lateral(spark, sf):
    """The two least suppliers of each nation, by a lateral subquery."""
    table(spark, sf, "nation").createOrReplaceTempView("lateral_nations")
    table(spark, sf, "supplier").createOrReplaceTempView("lateral_suppliers")
    return spark.sql(
        "SELECT n_nationkey, s_suppkey FROM lateral_nations, LATERAL (SELECT s_suppkey FROM lateral_suppliers WHERE s_nationkey = n_nationkey ORDER BY s_suppkey LIMIT 2)"
    )


def sql_path_view(spark, sf):
    udfs.create_path_view(spark, "nations_near", graphs.geography(spark, sf), "?x in_region/^in_region ?y")
    return spark.sql("SELECT x, count(*) AS n FROM nations_near WHERE x <> y GROUP BY x")


def udf_zorder(spark, sf):
    udfs.register(spark)
    graphs.cells(spark, sf, 7).createOrReplaceTempView("zorder_cells")
    return spark.sql("SELECT r, c, zorder_udf(r, c) AS z FROM zorder_cells")


def udtf_quadrants(spark, sf):
    """The quadrants on the way to each cell of a thin matrix, by a table function."""
    udfs.register(spark)
    graphs.cells(spark, sf, 3).createOrReplaceTempView("quadrant_cells")
    return spark.sql("SELECT q.depth, q.code, count(*) AS ones FROM quadrant_cells, LATERAL quadrants(r, c, 10) AS q GROUP BY q.depth, q.code")


def _quadrants_sql() -> str:
    spread = "list_sum(list_transform(range(0, depth), lambda k: ((r >> (9 - k)) & 1) * 2 * (1 << (2 * (depth - 1 - k))) + ((c >> (9 - k)) & 1) * (1 << (2 * (depth - 1 - k)))))"
    return f"SELECT CAST(depth AS BIGINT) AS depth, CAST({spread} AS BIGINT) AS code, count(*) AS ones FROM ({cells_sql(3)}) AS g, range(1, 11) AS d(depth) GROUP BY ALL"


def cells_sql(keep: int) -> str:
    """The counterpart of ``sources.graphs.cells``."""
    return f"SELECT DISTINCT l_partkey % 1000 AS r, l_orderkey % 1000 AS c FROM lineitem WHERE CAST(round(l_extendedprice * 100) AS BIGINT) % 100 = {keep}"


def grid_source(spark, sf):
    """Ones by rows of a matrix of lineitem."""
    ones = graphs.cells(spark, sf, 5)
    return ones.groupBy("r").agg(F.count("*").alias("ones"), F.sum("c").alias("total"))


def udaf_tile_or(spark, sf):
    """Payloads of tiles at one place are summed by an aggregate of users: click and view together."""

    @F.pandas_udf("binary")
    def merged(bits: pd.Series) -> bytes:
        total = qt.QuadTree.from_bytes(bits.iloc[0])
        for other in bits.iloc[1:]:
            total = qt.merge_sum(total, qt.QuadTree.from_bytes(other))
        return total.to_bytes()

    parts = [tiles.to_tiles(graphs.cells(spark, sf, keep), 6) for keep in (1, 2, 3)]
    together = parts[0].unionByName(parts[1]).unionByName(parts[2]).groupBy("tr", "tc").agg(merged("bits").alias("bits"))
    full = together.withColumn("flipped", F.lit(False))
    return tiles.from_tiles(full, 6)


def path_targets(spark, sf):
    return targets(graphs.commerce(spark, sf), "customer:7 ^placed_by/shipped_from/supp_in ?y")


def path_count(spark, sf):
    """How many pairs a closure has, counted by its components."""
    n = count_pairs(graphs.weblinks(spark, sf), "?x (links_to/^links_to)+ ?y")
    return spark.createDataFrame([("web_cluster", n)], "query string, n long")


def copy_groups(spark, sf):
    """Documents of equal text: representative and membership, no pairs."""
    from pathalgebra.operators.components import undirected_components

    return undirected_components(graphs.corpus(spark, sf).matrix("copy_of"))


def following_window(spark, sf):
    """The next event of each user and the time until then, in seconds."""
    by = Window.partitionBy("user_id").orderBy("ts", "event_id")
    rows = table(spark, sf, "events").withColumn("after", F.lead("event_id").over(by)).withColumn("then", F.lead("ts").over(by))
    return rows.where("after is not null").select("event_id", "after", F.expr("timestampdiff(SECOND, ts, then)").alias("seconds"))


def queries() -> dict[str, Query]:
    found = (
        edges_all, label_stats, web_links, pattern_star_join, degree_grouping_sets, rows_intersect, cast_ids, pair_struct, approx_nodes, bitmap_rows, top_neighbors_lateral,
        sql_path_view, udf_zorder, udtf_quadrants, grid_source, udaf_tile_or, path_targets, path_count, copy_groups, following_window,
    )
    return {f.__name__: f for f in found}


def oracle_sql() -> dict[str, str]:
    every = " UNION ALL ".join(f"SELECT '{p}' AS p, r, c FROM ({q}) AS m" for p, q in MATRICES["commerce"].items())
    rows = " FROM (SELECT r, list(DISTINCT c) AS v FROM ({}) AS m GROUP BY r)"
    click, view = (rows.format(MATRICES["activity"][p]) for p in ("click", "view"))
    zbits = " + ".join(f"(((r >> {k}) & 1) << {2 * k + 1}) + (((c >> {k}) & 1) << {2 * k})" for k in range(10))
    near = query_sql("geography", "?x in_region/^in_region ?y")
    return {
        "edges_all": f"SELECT r AS s, 'in_region' AS p, c AS o FROM ({MATRICES['geography']['in_region']}) AS m",
        "label_stats": f"SELECT p, count(*) AS ones, count(DISTINCT r) AS subjects, count(DISTINCT c) AS objects FROM ({every}) AS e GROUP BY p",
        "web_links": "SELECT page_id, count(*) AS links, count(DISTINCT href) AS addresses, count(*) FILTER (href[1] = '/') AS inside "
        "FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages) AS l GROUP BY page_id",
        "pattern_star_join": _star_sql(),
        "degree_grouping_sets": "SELECT coalesce(l_returnflag, 'all') AS flag, coalesce(l_linestatus, 'all') AS status, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())",
        "rows_intersect": f"SELECT x.r, CAST(len(list_intersect(x.v, y.v)) AS BIGINT) AS n, coalesce(array_to_string(list_sort(list_intersect(x.v, y.v)), ','), '') AS shared FROM (SELECT *{click}) AS x JOIN (SELECT *{view}) AS y ON x.r = y.r",
        "cast_ids": "SELECT p_partkey, TRY_CAST(p_brand AS BIGINT) AS brand, CAST(TRY_CAST(CAST(p_partkey AS VARCHAR) AS INTEGER) AS BIGINT) AS key, CAST(p_partkey AS VARCHAR) AS text FROM part",
        "pair_struct": f"SELECT r AS x, c + 1 AS y FROM ({MATRICES['geography']['in_region']}) AS m",
        "approx_nodes": f"SELECT p, CAST(100 AS BIGINT) AS percent FROM ({every}) AS e GROUP BY p",
        "bitmap_rows": "SELECT c_nationkey, count(DISTINCT c_custkey) AS n FROM customer GROUP BY c_nationkey",
        "top_neighbors_lateral": "SELECT n_nationkey, s_suppkey FROM (SELECT s_nationkey AS n_nationkey, s_suppkey, row_number() OVER (PARTITION BY s_nationkey ORDER BY s_suppkey) AS k FROM supplier) AS s WHERE k <= 2",
        "sql_path_view": f"SELECT x, count(*) AS n FROM ({near}) AS q WHERE x <> y GROUP BY x",
        "udf_zorder": f"SELECT r, c, CAST({zbits} AS BIGINT) AS z FROM ({cells_sql(7)}) AS g",
        "udtf_quadrants": _quadrants_sql(),
        "grid_source": f"SELECT r, count(*) AS ones, CAST(sum(c) AS BIGINT) AS total FROM ({cells_sql(5)}) AS g GROUP BY r",
        "udaf_tile_or": " UNION ".join(f"SELECT r, c FROM ({cells_sql(keep)}) AS g{keep}" for keep in (1, 2, 3)),
        "path_targets": f"SELECT DISTINCT y FROM ({query_sql('commerce', 'customer:7 ^placed_by/shipped_from/supp_in ?y')}) AS q",
        "path_count": f"SELECT 'web_cluster' AS query, count(*) AS n FROM ({query_sql('weblinks', '?x (links_to/^links_to)+ ?y')}) AS q",
        "copy_groups": "SELECT 10000000000000 + doc_id AS id, 10000000000000 + min(doc_id) OVER (PARTITION BY text) AS comp FROM documents WHERE text IN (SELECT text FROM documents GROUP BY text HAVING count(*) > 1)",
        "following_window": "SELECT event_id, after, CAST(floor(epoch(following) - epoch(ts)) AS BIGINT) AS seconds FROM (SELECT event_id, ts, lead(event_id) OVER w AS after, lead(ts) OVER w AS following FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) AS e WHERE after IS NOT NULL",
    }

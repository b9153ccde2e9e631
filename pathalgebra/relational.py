"""Operators around the algebra that a user of graphs on tables needs, with their SQL.

Each entry is one DataFrame plan and the same in SQL; results are whole numbers
and strings, so that both engines agree to the last digit.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pathalgebra.runtime import table
from pathalgebra.sources.graphs import following

Query = Callable[[SparkSession, str], DataFrame]


def _cents(column: str):
    return F.round(F.col(column) * 100).cast("long")


def label_pivot(spark, sf):
    """Events of each user by type, one column for each type."""
    return table(spark, sf, "events").groupBy("user_id").pivot("event_type", ["click", "error", "purchase", "signup", "view"]).count().na.fill(0)


def degree_cube(spark, sf):
    rows = table(spark, sf, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.countDistinct("l_suppkey").alias("suppliers"))
    return rows.select(F.coalesce("l_returnflag", F.lit("all")).alias("flag"), F.coalesce("l_linestatus", F.lit("all")).alias("status"), "n", "suppliers")


def degree_rollup(spark, sf):
    rows = table(spark, sf, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.sum(_cents("l_extendedprice")).alias("cents"))
    return rows.select(F.coalesce("l_returnflag", F.lit("all")).alias("flag"), F.coalesce("l_linestatus", F.lit("all")).alias("status"), "cents")


def degree_percentiles(spark, sf):
    degree = table(spark, sf, "orders").groupBy("o_custkey").agg(F.count("*").alias("n"))
    return degree.agg(*(F.expr(f"cast(round(percentile(n, {p / 100}) * 100) as bigint)").alias(f"p{p}") for p in (10, 50, 90, 99)))


def degree_with_zero(spark, sf):
    """Orders of every customer, none included."""
    orders = table(spark, sf, "orders").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.count("*").alias("n"))
    return table(spark, sf, "customer").join(orders, "c_custkey", "left").select("c_custkey", F.coalesce("n", F.lit(0)).alias("n"))


def nodes_without_out(spark, sf):
    return table(spark, sf, "customer").join(table(spark, sf, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


def filter_label(spark, sf):
    rows = table(spark, sf, "lineitem").where("l_returnflag in ('A', 'N') and l_quantity between 10 and 20 and l_linestatus like 'O%'")
    return rows.select("l_orderkey", "l_linenumber", "l_partkey")


def join_broadcast(spark, sf):
    nations = table(spark, sf, "nation")  # 25 rows
    return table(spark, sf, "supplier").join(F.broadcast(nations), F.col("s_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


def range_quadrant(spark, sf):
    """Orders by the quadrant of (customer, order) that they fall in; halves of both ranges."""
    orders = table(spark, sf, "orders")
    side = orders.agg((F.max("o_custkey") + 1).alias("v"), (F.max("o_orderkey") + 1).alias("w"))
    halves = orders.join(F.broadcast(side))
    quadrant = F.expr("2 * int(2 * o_custkey >= v) + int(2 * o_orderkey >= w)").cast("long").alias("quadrant")
    return halves.select(quadrant).groupBy("quadrant").agg(F.count("*").alias("n"))


def interval_edges(spark, sf):
    """Views of a user within an hour before a purchase; bins of an hour make it an equi-join."""
    events = table(spark, sf, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    hour = 3_600_000_000
    buys = events.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase"), F.col("t").alias("until"))
    buys = buys.withColumn("bin", F.explode(F.array(F.expr(f"until div {hour}"), F.expr(f"until div {hour} - 1"))))
    views = events.where("event_type = 'view'").select("user_id", F.col("event_id").alias("viewed"), "t", F.expr(f"t div {hour}").alias("bin"))
    return buys.join(views, ["user_id", "bin"]).where(f"t <= until and t > until - {hour}").select("purchase", "viewed")


def asof_edge(spark, sf):
    """Each purchase with the same user's last view before it, by a window over both."""
    by = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(by)
    return table(spark, sf, "events").withColumn("viewed", last).where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "viewed")


def rank_labels(spark, sf):
    n = table(spark, sf, "part").groupBy("p_brand", "p_size").agg(F.count("*").alias("n"))
    by = Window.partitionBy("p_brand").orderBy(F.desc("n"))
    return n.select("p_brand", "p_size", "n", F.rank().over(by).cast("long").alias("rank"), F.dense_rank().over(by).cast("long").alias("dense"))


def running_rank(spark, sf):
    """Running sums of orders by customer and day, and over three rows."""
    by = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    cents = _cents("o_totalprice")
    return table(spark, sf, "orders").select("o_orderkey", F.sum(cents).over(by.rowsBetween(Window.unboundedPreceding, 0)).alias("running"), F.sum(cents).over(by.rowsBetween(-1, 1)).alias("near"))


def first_last_event(spark, sf):
    return table(spark, sf, "events").groupBy("user_id").agg(F.min_by("event_type", F.struct("ts", "event_id")).alias("first"), F.max_by("event_type", F.struct("ts", "event_id")).alias("last"))


def topk_labels(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_suppkey").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "l_suppkey").limit(10)


def setops(spark, sf):
    """Parts by how the suppliers' lists of two flags meet: union, intersection, difference."""
    items = table(spark, sf, "lineitem")
    a = items.where("l_returnflag = 'A'").select("l_partkey").distinct()
    r = items.where("l_returnflag = 'R'").select("l_partkey").distinct()
    parts = [("union", a.union(r).distinct()), ("intersect", a.intersect(r)), ("except", a.exceptAll(r))]
    out = [x.select(F.lit(k).alias("op"), "l_partkey") for k, x in parts]
    return out[0].unionByName(out[1]).unionByName(out[2]).groupBy("op").agg(F.count("*").alias("n"), F.sum("l_partkey").alias("total"))


def url_parts(spark, sf):
    return table(spark, sf, "pages").select(
        "page_id", F.regexp_extract("url", "^([a-z]+)://", 1).alias("scheme"), F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"), F.lower(F.regexp_extract("url", "^[a-z]+://[^/]+(/[^?#]*)", 1)).alias("path"),
        F.length("url").cast("long").alias("n"),
    )


def orders_by_month(spark, sf):
    month = F.date_format(F.date_trunc("month", F.col("o_orderdate")), "yyyy-MM")
    return table(spark, sf, "orders").groupBy(month.alias("month")).agg(F.count("*").alias("n"), F.sum(_cents("o_totalprice")).alias("cents"))


def popcount_rows(spark, sf):
    """A customer's order days of the month as a bitmap, and how many."""
    bit = F.expr("shiftleft(cast(1 as bigint), day(o_orderdate))")
    return table(spark, sf, "orders").groupBy("o_custkey").agg(F.bit_or(bit).alias("bits")).select("o_custkey", "bits", F.bit_count("bits").cast("long").alias("days"))


def rows_merge(spark, sf):
    """Rows of two matrices merged as arrays: parts of each supplier by flag, both and either."""
    items = table(spark, sf, "lineitem")
    rows = items.groupBy("l_suppkey").agg(F.collect_set(F.when(F.col("l_returnflag") == "A", F.col("l_partkey"))).alias("a"), F.collect_set(F.when(F.col("l_returnflag") == "R", F.col("l_partkey"))).alias("r"))
    both, either = F.array_intersect("a", "r"), F.array_union("a", "r")
    total = F.aggregate(either, F.lit(0).cast("long"), lambda acc, x: acc + x)
    return rows.select("l_suppkey", F.size(both).cast("long").alias("both"), F.size(either).cast("long").alias("either"), total.alias("total"))


def label_histogram(spark, sf):
    """Types of events of a user as a map, read back by key."""
    counts = table(spark, sf, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    maps = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return maps.select("user_id", F.coalesce(F.element_at("m", "click"), F.lit(0)).alias("clicks"), F.size(F.map_keys("m")).cast("long").alias("types"))


def events_props(spark, sf):
    return table(spark, sf, "events").groupBy(F.from_json("props", "k int")["k"].cast("long").alias("k")).agg(F.count("*").alias("n"))


def null_safe_pairs(spark, sf):
    """Documents by null-safe language and labelled quality; missing labels form a group."""
    docs, labels = table(spark, sf, "documents").select("doc_id", "lang"), table(spark, sf, "labels").select("doc_id", "quality")
    return docs.join(labels, "doc_id", "left").groupBy(F.coalesce("lang", F.lit("-")).alias("lang"), F.coalesce(F.col("quality").cast("string"), F.lit("-")).alias("quality")).agg(F.count("*").alias("n"))


def activity_edges(spark, sf):
    """Every event with the next one of all, across partitions."""
    events = table(spark, sf, "events").select("ts", "event_id", "user_id")
    return following(events, ["ts", "event_id"], ["event_id"]).select("event_id", "next_event_id")


def exists_filter(spark, sf):
    """Customers with an order above the mean of all orders."""
    orders = table(spark, sf, "orders")
    mean = orders.agg((F.sum(_cents("o_totalprice")) / F.count("*")).alias("mean"))  # one row
    rich = orders.join(F.broadcast(mean)).where(_cents("o_totalprice") > F.col("mean"))
    return table(spark, sf, "customer").join(rich, F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


def unpivot_measures(spark, sf):
    rows = table(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.sum(F.col("l_quantity").cast("long")).alias("quantity"), F.count("*").alias("items"))
    return rows.unpivot("l_returnflag", ["quantity", "items"], "measure", "value")


def bounded_walks(spark, sf):
    """Walks of up to five steps from the first event, by a recursive common table."""
    events = table(spark, sf, "events")
    by = Window.partitionBy("user_id").orderBy("ts", "event_id")
    events.select("event_id", F.lead("event_id").over(by).alias("after")).createOrReplaceTempView("pathalgebra_next_event")
    return spark.sql("WITH RECURSIVE w(event_id, k) AS (SELECT CAST(0 AS BIGINT), 0 UNION ALL SELECT n.after, w.k + 1 FROM w JOIN pathalgebra_next_event AS n ON n.event_id = w.event_id WHERE w.k < 5 AND n.after IS NOT NULL) SELECT event_id, CAST(k AS BIGINT) AS k FROM w")


def queries() -> dict[str, Query]:
    found = (
        label_pivot, degree_cube, degree_rollup, degree_percentiles, degree_with_zero, nodes_without_out, filter_label, join_broadcast, range_quadrant, interval_edges, asof_edge, rank_labels, running_rank,
        first_last_event, topk_labels, setops, url_parts, orders_by_month, popcount_rows, rows_merge, label_histogram, events_props, null_safe_pairs, activity_edges, exists_filter, unpivot_measures, bounded_walks,
    )
    return {f.__name__: f for f in found}


def oracle_sql() -> dict[str, str]:
    cents = "CAST(round({} * 100) AS BIGINT)"
    total, price = cents.format("o_totalprice"), cents.format("l_extendedprice")
    types = ("click", "error", "purchase", "signup", "view")
    by = "(PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN {} AND {})"
    return {
        "label_pivot": f"SELECT user_id, {', '.join(f'''count(*) FILTER (event_type = '{t}') AS {t}''' for t in types)} FROM events GROUP BY user_id",
        "degree_cube": "SELECT coalesce(l_returnflag, 'all') AS flag, coalesce(l_linestatus, 'all') AS status, count(*) AS n, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)",
        "degree_rollup": f"SELECT coalesce(l_returnflag, 'all') AS flag, coalesce(l_linestatus, 'all') AS status, CAST(sum({price}) AS BIGINT) AS cents FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)",
        "degree_percentiles": f"SELECT {', '.join(f'CAST(round(quantile_cont(n, {p / 100}) * 100) AS BIGINT) AS p{p}' for p in (10, 50, 90, 99))} FROM (SELECT count(*) AS n FROM orders GROUP BY o_custkey) AS d",
        "degree_with_zero": "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey",
        "nodes_without_out": "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)",
        "filter_label": "SELECT l_orderkey, l_linenumber, l_partkey FROM lineitem WHERE l_returnflag IN ('A', 'N') AND l_quantity BETWEEN 10 AND 20 AND l_linestatus LIKE 'O%'",
        "join_broadcast": "SELECT n_name, count(*) AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY n_name",
        "range_quadrant": "SELECT CAST(2 * (2 * o_custkey >= v)::INT + (2 * o_orderkey >= w)::INT AS BIGINT) AS quadrant, count(*) AS n FROM orders, (SELECT max(o_custkey) + 1 AS v, max(o_orderkey) + 1 AS w FROM orders) AS s GROUP BY ALL",
        "interval_edges": "SELECT p.event_id AS purchase, v.event_id AS viewed FROM events AS p JOIN events AS v ON p.user_id = v.user_id AND p.event_type = 'purchase' AND v.event_type = 'view' AND v.ts <= p.ts AND v.ts > p.ts - INTERVAL 1 HOUR",
        "asof_edge": "SELECT event_id AS purchase, viewed FROM (SELECT *, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS viewed FROM events) AS e WHERE event_type = 'purchase'",
        "rank_labels": "SELECT p_brand, p_size, n, rank() OVER w AS rank, dense_rank() OVER w AS dense FROM (SELECT p_brand, p_size, count(*) AS n FROM part GROUP BY ALL) AS c WINDOW w AS (PARTITION BY p_brand ORDER BY n DESC)",
        "running_rank": f"SELECT o_orderkey, CAST(sum({total}) OVER {by.format('UNBOUNDED PRECEDING', 'CURRENT ROW')} AS BIGINT) AS running, CAST(sum({total}) OVER {by.format('1 PRECEDING', '1 FOLLOWING')} AS BIGINT) AS near FROM orders",
        "first_last_event": "SELECT user_id, arg_min(event_type, (ts, event_id)) AS first, arg_max(event_type, (ts, event_id)) AS last FROM events GROUP BY user_id",
        "topk_labels": "SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY l_suppkey ORDER BY n DESC, l_suppkey LIMIT 10",
        "setops": "WITH a AS (SELECT DISTINCT l_partkey FROM lineitem WHERE l_returnflag = 'A'), r AS (SELECT DISTINCT l_partkey FROM lineitem WHERE l_returnflag = 'R') SELECT op, count(*) AS n, CAST(sum(l_partkey) AS BIGINT) AS total FROM (SELECT 'union' AS op, * FROM (SELECT * FROM a UNION SELECT * FROM r) AS x UNION ALL SELECT 'intersect', * FROM (SELECT * FROM a INTERSECT SELECT * FROM r) AS y UNION ALL SELECT 'except', * FROM (SELECT * FROM a EXCEPT SELECT * FROM r) AS z) AS u GROUP BY op",
        "url_parts": "SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, lower(regexp_extract(url, '^[a-z]+://[^/]+(/[^?#]*)', 1)) AS path, length(url) AS n FROM pages",
        "orders_by_month": f"SELECT strftime(o_orderdate, '%Y-%m') AS month, count(*) AS n, CAST(sum({total}) AS BIGINT) AS cents FROM orders GROUP BY 1",
        "popcount_rows": "SELECT o_custkey, bits, CAST(bit_count(bits) AS BIGINT) AS days FROM (SELECT o_custkey, bit_or(CAST(1 AS BIGINT) << day(o_orderdate)) AS bits FROM orders GROUP BY o_custkey) AS b",
        "rows_merge": "SELECT l_suppkey, CAST(count(*) FILTER (a AND r) AS BIGINT) AS both, CAST(count(*) FILTER (a OR r) AS BIGINT) AS either, CAST(coalesce(sum(l_partkey) FILTER (a OR r), 0) AS BIGINT) AS total FROM (SELECT l_suppkey, l_partkey, bool_or(l_returnflag = 'A') AS a, bool_or(l_returnflag = 'R') AS r FROM lineitem GROUP BY ALL) AS x GROUP BY l_suppkey",
        "label_histogram": "SELECT user_id, count(*) FILTER (event_type = 'click') AS clicks, count(DISTINCT event_type) AS types FROM events GROUP BY user_id",
        "events_props": "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1",
        "null_safe_pairs": "SELECT coalesce(lang, '-') AS lang, coalesce(CAST(quality AS VARCHAR), '-') AS quality, count(*) AS n FROM documents LEFT JOIN labels USING (doc_id) GROUP BY 1, 2",
        "activity_edges": "SELECT event_id, lead(event_id) OVER (ORDER BY ts, event_id) AS next_event_id FROM events",
        "exists_filter": f"SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND {total} > (SELECT sum({total}) / count(*) FROM orders))",
        "unpivot_measures": "SELECT l_returnflag, 'quantity' AS measure, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS value FROM lineitem GROUP BY 1 UNION ALL SELECT l_returnflag, 'items', count(*) FROM lineitem GROUP BY 1",
        "bounded_walks": "WITH RECURSIVE n AS (SELECT event_id, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS after FROM events), w(event_id, k) AS (SELECT CAST(0 AS BIGINT), CAST(0 AS BIGINT) UNION ALL SELECT n.after, w.k + 1 FROM w JOIN n ON n.event_id = w.event_id WHERE w.k < 5 AND n.after IS NOT NULL) SELECT event_id, k FROM w",
    }

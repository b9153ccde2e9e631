"""Registered streaming queries; their results equal the batch ones, which tests check."""

from __future__ import annotations

from pathalgebra.operators.closure import closure
from pathalgebra.operators.matrix import union
from pathalgebra.plans.to_sql import matrix_sql
from pathalgebra.runtime import checkpointed, table
from pathalgebra.sources import graphs
from pathalgebra.streaming import edges


def stream_tumbling(spark, sf):
    return edges.run_once(edges.windowed_counts(edges.edge_stream(spark, f"{sf}/events.parquet")), "tumbling")


def stream_sliding(spark, sf):
    counts = edges.windowed_counts(edges.edge_stream(spark, f"{sf}/events.parquet"), "1 day", "6 hours")
    return edges.run_once(counts, "sliding")


def stream_session(spark, sf):
    return edges.run_once(edges.session_counts(edges.edge_stream(spark, f"{sf}/events.parquet")), "session")


def stream_static(spark, sf):
    """Events of customers, with the market segment from a table."""
    customers = table(spark, sf, "customer").select("c_custkey", "c_mktsegment")
    joined = edges.with_static(edges.edge_stream(spark, f"{sf}/events.parquet"), customers, "user_id", "c_custkey")
    return edges.run_once(joined.select("event_id", "c_mktsegment"), "static", "append")


def stream_interval(spark, sf):
    """Purchases within an hour after a click of the same user."""
    return edges.run_once(edges.pairs_within(edges.edge_stream(spark, f"{sf}/events.parquet"), "click", "purchase"), "interval", "append")


def incremental_closure(spark, sf):
    """A closure that is kept up to date when the second half of its edges arrives."""
    g = graphs.succession(spark, sf)
    whole = checkpointed(union(g.matrix("click"), g.matrix("view")))
    early, late = whole.where("r % 2 = 0"), whole.where("r % 2 <> 0")
    return edges.add_edges(closure(early), early, late)


def queries():
    return {f.__name__: f for f in (stream_tumbling, stream_sliding, stream_session, stream_static, stream_interval, incremental_closure)}


def oracle_sql() -> dict[str, str]:
    sessions = (
        "WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), "
        "s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) "
        "SELECT CAST(floor(epoch(min(ts))) AS BIGINT) AS start, user_id, count(*) AS n FROM s GROUP BY user_id, k"
    )
    start = "CAST(epoch(date_trunc('day', ts)) AS BIGINT)"
    slot = "CAST(floor(epoch(ts) / 21600) AS BIGINT) * 21600"
    return {
        "stream_tumbling": f"SELECT {start} AS start, event_type, count(*) AS n FROM events GROUP BY ALL",
        "stream_sliding": f"SELECT {slot} - k * 21600 AS start, event_type, count(*) AS n FROM events, range(4) AS t(k) GROUP BY ALL",
        "stream_session": sessions,
        "stream_static": "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey",
        "stream_interval": "SELECT a.user_id, a.event_id, b.event_id AS after FROM events AS a JOIN events AS b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' "
        "AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR",
        "incremental_closure": f"SELECT r, c FROM ({matrix_sql('succession', '(click|view)+')}) AS q",
    }

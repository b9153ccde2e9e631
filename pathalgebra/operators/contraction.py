"""Connected components of an undirected edge table, by alternating star contraction.

Every round points each vertex at the least neighbour it knows, first for the
larger neighbours, then for the smaller ones; chains halve, so the rounds grow
with the logarithm of the longest path.  No vertex's neighbours are gathered:
a round is one aggregate that combines before its shuffle and one plain join,
whose large partitions Spark may split.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathalgebra.runtime import kept, scratch, stored


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """One contraction; ``edges`` (a > b) are distinct, and so are those that come out."""
    down = edges.select(F.col("a").alias("u"), F.col("b").alias("v"))
    both = down.unionByName(edges.select(F.col("b").alias("u"), F.col("a").alias("v"))) if large else down
    least = both.groupBy(F.col("u").alias("k")).agg(F.min("v").alias("m")).select("k", F.least("k", "m").alias("m"))
    joined = both.join(least, both["u"] == least["k"])
    if large:
        out = joined.where("v > u").select(F.col("v").alias("a"), F.col("m").alias("b"))
    else:
        out = joined.where("v <> m").select(F.col("v").alias("a"), F.col("m").alias("b"))
        out = out.unionByName(least.where("k <> m").select(F.col("k").alias("a"), F.col("m").alias("b")))
    return out.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()


def _mark(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())


def connected(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(id, component_id) of all ends of ``edges`` (a, b); the least id names a component.

    Ends are whole numbers without nulls; loops and repeated edges don't matter.
    Ends that have loops only, and no edges at all, give no rows.
    """
    with scratch(edges.sparkSession):
        pairs = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        edges = stored(pairs.where("a <> b").distinct(), "edges")
        before = _mark(edges)
        for _ in range(most_rounds if before[0] else 0):
            edges = stored(_star(stored(_star(edges, large=True), "star"), large=False), "star")
            now = _mark(edges)
            if now == before:
                break
            before = now
        else:
            if before[0]:
                raise RuntimeError("components didn't settle")
        pointers = edges.select(F.col("a").alias("id"), F.col("b").alias("component_id"))
        roots = pointers.select(F.col("component_id").alias("id"), "component_id").distinct()
        return kept(pointers.unionByName(roots), "components")

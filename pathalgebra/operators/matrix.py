"""Boolean matrices as relations of their ones, and the operations on them.

A matrix is a frame with columns ``r`` and ``c``, one row for each one.  All
operations return distinct rows; ``row`` and ``col`` restrict a result to one
line, and the restriction is placed before the operation, so that it reaches the
scan.  Transposition exchanges the names of the two columns and costs nothing.
"""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def matrix(df: DataFrame, r: str = "r", c: str = "c", distinct: bool = False) -> DataFrame:
    """A matrix from two columns; rows with a null end hold no one."""
    out = df.select(F.col(r).alias("r"), F.col(c).alias("c")).where("r is not null and c is not null")
    return out if distinct else out.distinct()


def empty(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([], "r long, c long")


def identity(nodes: DataFrame) -> DataFrame:
    """Ones at (v, v) for each ``id``."""
    return nodes.select(F.col("id").alias("r"), F.col("id").alias("c"))


def transpose(a: DataFrame) -> DataFrame:
    return a.select(F.col("c").alias("r"), F.col("r").alias("c"))


def restrict(a: DataFrame, row: int | None = None, col: int | None = None) -> DataFrame:
    if row is not None:
        a = a.where(F.col("r") == row)
    if col is not None:
        a = a.where(F.col("c") == col)
    return a


def union(a: DataFrame, b: DataFrame, row: int | None = None, col: int | None = None) -> DataFrame:
    return restrict(a, row, col).unionByName(restrict(b, row, col)).distinct()


def union_all(parts: Sequence[DataFrame]) -> DataFrame:
    """Sum of many: one union and one aggregate, whatever the order."""
    return reduce(lambda x, y: x.unionByName(y), parts).distinct()


def intersect(a: DataFrame, b: DataFrame, row: int | None = None, col: int | None = None) -> DataFrame:
    return restrict(a, row, col).join(restrict(b, row, col), ["r", "c"], "left_semi")


def minus(a: DataFrame, b: DataFrame, row: int | None = None, col: int | None = None) -> DataFrame:
    return restrict(a, row, col).join(restrict(b, row, col), ["r", "c"], "left_anti")


def xor(a: DataFrame, b: DataFrame, row: int | None = None, col: int | None = None) -> DataFrame:
    both = restrict(a, row, col).unionByName(restrict(b, row, col))
    return both.groupBy("r", "c").agg(F.count("*").alias("n")).where("n = 1").select("r", "c")


def xor_outer(a: DataFrame, b: DataFrame) -> DataFrame:
    """The same by a full outer join, as tiles are matched."""
    left, right = a.withColumn("in_a", F.lit(1)), b.withColumn("in_b", F.lit(1))
    return left.join(right, ["r", "c"], "full_outer").where("in_a is null or in_b is null").select("r", "c")


def _meet(a: DataFrame, b: DataFrame) -> DataFrame:
    # Both sides get a new name for the middle index; see the note on loops in the README.
    return a.select("r", F.col("c").alias("k")).join(b.select(F.col("r").alias("k"), "c"), "k")


def product(a: DataFrame, b: DataFrame, row: int | None = None, col: int | None = None, method: str = "outer", heavy: int = 100_000) -> DataFrame:
    """Boolean product: rows of the left factor, columns of the right one are restricted first.

    ``outer`` matches columns of A with rows of B and pairs what stands there;
    ``rowwise`` joins with B's rows as arrays and merges them row by row, but for
    rows into which more than ``heavy`` ones would be merged, which go the other way;
    ``salted`` deals middle indices with more than ``heavy`` ones in A over several
    tasks and copies their rows of B.
    """
    a, b = restrict(a, row=row), restrict(b, col=col)
    if method == "rowwise":
        rows = adjacency_rows(b).withColumnRenamed("r", "k")
        wide = a.join(rows.select(F.col("k").alias("c"), F.size("cols").alias("n")), "c").groupBy("r").agg(F.sum("n").alias("n")).where(F.col("n") > heavy).select("r")
        joined = a.join(wide, "r", "left_anti").select("r", F.col("c").alias("k")).join(rows, "k")
        merged = joined.groupBy("r").agg(F.array_distinct(F.flatten(F.collect_list("cols"))).alias("cols"))
        return merged.select("r", F.explode("cols").alias("c")).unionByName(_meet(a.join(wide, "r", "left_semi"), b).select("r", "c").distinct())
    if method == "salted":
        fan = 8
        loaded = a.groupBy(F.col("c").alias("k")).agg(F.count("*").alias("n")).where(F.col("n") > heavy).select("k", F.lit(True).alias("heavy"))
        salt = F.when(F.col("heavy"), F.pmod(F.xxhash64("r"), F.lit(fan)).cast("int")).otherwise(0)
        left = a.select("r", F.col("c").alias("k")).join(loaded, "k", "left").select("r", "k", salt.alias("salt"))
        salts = F.when(F.col("heavy"), F.sequence(F.lit(0), F.lit(fan - 1))).otherwise(F.array(F.lit(0)))
        right = b.select(F.col("r").alias("k"), "c").join(loaded, "k", "left").select("k", "c", F.explode(salts).alias("salt"))
        return left.join(right, ["k", "salt"]).select("r", "c").distinct()
    return _meet(a, b).select("r", "c").distinct()


def product_counts(a: DataFrame, b: DataFrame) -> DataFrame:
    """The numeric product: how many middle indices witness each one."""
    return _meet(a, b).groupBy("r", "c").agg(F.count("*").alias("walks"))


def adjacency_rows(a: DataFrame) -> DataFrame:
    """(r, cols): each row's columns as a sorted array."""
    return a.groupBy("r").agg(F.array_sort(F.collect_set("c")).alias("cols"))


def power(a: DataFrame, k: int) -> DataFrame:
    """Walks of exactly ``k`` steps, by repeated squaring."""
    if k < 1:
        raise ValueError("power needs at least one step")
    result, square = None, a
    while k:
        if k & 1:
            result = square if result is None else product(result, square)
        k >>= 1
        if k:
            square = product(square, square)
    return result


def within(a: DataFrame, k: int, nodes: DataFrame) -> DataFrame:
    """Pairs joined by at most ``k`` steps: powers of identity plus A."""
    return power(union(identity(nodes), a), k)


def triangles(a: DataFrame) -> DataFrame:
    """Pairs (r, c) with a walk of two steps there and a step back."""
    return intersect(product(a, a), transpose(a))

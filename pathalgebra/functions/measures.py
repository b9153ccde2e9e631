"""Cost measures: space, density, alternation, latency."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pathalgebra.functions.zorder import zorder
from pathalgebra.runtime import checkpointed


def raw_pair_bytes(edges: int) -> int:
    """Two 32-bit numbers an edge."""
    return 8 * edges


def stored_bytes(spark, path: str) -> int:
    """Bytes of the files below a path, in any file system Spark knows."""
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    fs = where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    return fs.getContentSummary(where).getLength()


def bytes_per_triple(spark, path: str, triples: int) -> float:
    return stored_bytes(spark, path) / max(1, triples)


def label_stats(triples: DataFrame) -> DataFrame:
    """(p, ones, subjects, objects)."""
    return triples.groupBy("p").agg(F.count("*").alias("ones"), F.countDistinct("s").alias("subjects"), F.countDistinct("o").alias("objects"))


def expected_product_density(side: int, d1: float, d2: float) -> float:
    return side * d1 * d2


def alternation(a: DataFrame, b: DataFrame, kind: str = "certificate") -> int:
    """How often one must change between A and B when walking both in z-order.

    ``certificate`` (for intersection) counts every common point and every change
    between points of one side only; ``switches`` (for union and xor) counts
    changes of the side.  Range-partitioned; two tags for each partition meet on
    the driver.
    """
    points = a.select(zorder(F.col("r"), F.col("c")).alias("z"), F.lit(1).alias("side"))
    points = points.unionByName(b.select(zorder(F.col("r"), F.col("c")).alias("z"), F.lit(2).alias("side")))
    tagged = points.groupBy("z").agg(F.sum("side").alias("side"))
    if kind == "switches":
        tagged = tagged.where("side <> 3")
    placed = checkpointed(tagged.repartitionByRange("z").sortWithinPartitions("z").withColumn("part", F.spark_partition_id()))
    by = Window.partitionBy("part").orderBy("z")
    change = (F.lag("side").over(by) != F.col("side")).cast("int")
    steps = placed.withColumn("step", F.coalesce(F.when(F.col("side") == 3, 1).otherwise(change), F.lit(0)) if kind == "certificate" else F.coalesce(change, F.lit(0)))
    per = steps.groupBy("part").agg(F.sum("step").alias("n"), F.min_by("side", "z").alias("first"), F.max_by("side", "z").alias("last")).orderBy("part").collect()
    total = sum(r["n"] for r in per)
    for left, right in zip(per, per[1:], strict=False):
        total += int(left["last"] != right["first"] and right["first"] != 3)
    return total


def latency_table(timings: DataFrame) -> DataFrame:
    """Mean, median and timeouts by engine: all queries, and with or without a constant."""
    sets = timings.rollup("engine", "has_const").agg(
        F.avg("seconds").alias("mean_s"), F.percentile("seconds", 0.5).alias("median_s"), F.percentile("seconds", 0.9).alias("p90_s"), F.count_if("timed_out").alias("timeouts")
    )
    return sets.where("engine is not null")

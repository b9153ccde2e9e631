"""Physical layouts: plain pairs, two redundant sorted views, and tiles."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathalgebra.operators.tiles import to_tiles
from pathalgebra.runtime import fresh_path
from pathalgebra.sources.graphs import Graph


def write_pairs(triples: DataFrame, path: str) -> None:
    """(s, o) by label, one folder each: the raw form."""
    triples.write.mode("overwrite").partitionBy("p").parquet(path)


def write_dual(triples: DataFrame, name: str, buckets: int = 16) -> tuple[str, str]:
    """Two tables, bucketed and sorted by either end, so that a product of two labels joins without an exchange.

    Labels are partitions, so a label's scan reads its own files only.
    """
    spark, by_s, by_o = triples.sparkSession, f"{name}_by_s", f"{name}_by_o"
    for table, first, second in ((by_s, "s", "o"), (by_o, "o", "s")):
        writer = triples.select("s", "o", "p").write.mode("overwrite").option("path", fresh_path(spark, table))
        writer.partitionBy("p").bucketBy(buckets, first).sortBy(first, second).saveAsTable(table)
    return by_s, by_o


def drop_dual(spark: SparkSession, name: str) -> None:
    """Forget the tables' names; the files stay in the shared folder."""
    for end in "so":
        spark.sql(f"DROP TABLE IF EXISTS {name}_by_{end}")


class DualGraph(Graph):
    """A graph in the dual layout: every label by its rows and once more by its columns."""

    def __init__(self, spark: SparkSession, name: str):
        self.name = name
        labels = [r["p"] for r in spark.table(f"{name}_by_s").select("p").distinct().collect()]
        super().__init__(spark, {p: (lambda p=p: self._read(p, "s")) for p in labels})
        self._all = spark.table(f"{name}_by_s").select("s", "p", "o")

    @classmethod
    def write(cls, graph: Graph, name: str | None = None, buckets: int | None = None) -> DualGraph:
        """Store a graph; by default there are as many buckets as shuffle partitions."""
        name = name or f"dual_{uuid.uuid4().hex}"
        write_dual(graph.triples(), name, buckets or int(graph.spark.conf.get("spark.sql.shuffle.partitions")))
        return cls(graph.spark, name)

    def _read(self, label: str, end: str) -> DataFrame:
        return self.spark.table(f"{self.name}_by_{end}").where(F.col("p") == label).select(F.col("s").alias("r"), F.col("o").alias("c"))

    def view(self, label: str, by: str | None = None) -> DataFrame:
        if by != "c" or label not in self._make:
            return self.matrix(label)
        return self._read(label, "o")


def dual_product(spark: SparkSession, name: str, left: str, right: str) -> DataFrame:
    """Product of two labels of a dual layout: the column view of one meets the row view of the other."""
    a = spark.table(f"{name}_by_o").where(f"p = '{left}'").selectExpr("s as r", "o as k")
    b = spark.table(f"{name}_by_s").where(f"p = '{right}'").selectExpr("s as k", "o as c")
    return a.join(b.hint("merge"), "k").select("r", "c").distinct()


def write_tiles(matrix: DataFrame, path: str, tile_bits: int = 10) -> None:
    """One matrix over dense node numbers as quadtree tiles."""
    to_tiles(matrix, tile_bits).write.mode("overwrite").parquet(path)

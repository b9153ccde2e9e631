"""Triples from files of several formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed value: one statement of N-Triples; the object may be a name or a literal.
_STATEMENT = r'^\s*(<[^>]*>|_:\S+)\s+<([^>]*)>\s+(<[^>]*>|_:\S+|".*"\S*)\s*\.\s*$'


def read_triples(spark: SparkSession, path: str, fmt: str = "parquet", columns: tuple[str, str, str] = ("s", "p", "o")) -> DataFrame:
    """(s, p, o), distinct, without rows that lack one of them.

    ``fmt``: parquet, orc, json, csv, tsv (with a header) or ntriples.
    """
    if fmt == "ntriples":
        lines = spark.read.text(path)
        parts = [F.regexp_extract("value", _STATEMENT, k).alias(n) for k, n in ((1, "s"), (2, "p"), (3, "o"))]
        rows = lines.where(F.col("value").rlike(_STATEMENT)).select(*parts)
    elif fmt in ("csv", "tsv"):
        rows = spark.read.option("header", True).option("sep", "\t" if fmt == "tsv" else ",").csv(path)
    else:
        rows = spark.read.format(fmt).load(path)
    if fmt != "ntriples":
        rows = rows.select(*(F.col(c).alias(n) for c, n in zip(columns, ("s", "p", "o"), strict=True)))
    return rows.where("s is not null and p is not null and o is not null").distinct()


def encode_triples(triples: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Triples over dense node numbers, and the table (term, id) of all ends."""
    from pathalgebra.sources.graphs import dense_numbers

    names = dense_numbers(triples.select(F.col("s").alias("term")).union(triples.select(F.col("o").alias("term"))), "term")
    left, right = names.select(F.col("term").alias("s"), F.col("id").alias("sid")), names.select(F.col("term").alias("o"), F.col("id").alias("oid"))
    return triples.join(left, "s").join(right, "o").select(F.col("sid").alias("s"), "p", F.col("oid").alias("o")), names

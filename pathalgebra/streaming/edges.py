"""Edge streams: windows over arriving edges, and reachability kept up to date."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathalgebra.operators import matrix as m
from pathalgebra.runtime import checkpointed, fresh_path


def edge_stream(spark: SparkSession, path: str) -> DataFrame:
    """Events as a stream of files, with a time that a watermark can use."""
    schema = spark.read.parquet(path).schema
    # A file source wants a folder; a single file is found by its name.
    folder, _, name = path.rstrip("/").rpartition("/")
    reader = spark.readStream.schema(schema)
    stream = reader.option("pathGlobFilter", name).parquet(folder)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def windowed_counts(stream: DataFrame, length: str = "1 day", slide: str | None = None, late: str = "1 day") -> DataFrame:
    """Edges by window and type; rows later than ``late`` are dropped."""
    window = F.window("ts", length, slide) if slide else F.window("ts", length)
    counts = stream.withWatermark("ts", late).groupBy(window.alias("w"), "event_type").agg(F.count("*").alias("n"))
    return counts.select(F.unix_seconds("w.start").alias("start"), "event_type", "n")


def session_counts(stream: DataFrame, gap: str = "30 minutes", late: str = "1 day") -> DataFrame:
    counts = stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return counts.select(F.unix_seconds("w.start").alias("start"), "user_id", "n")


def with_static(stream: DataFrame, static: DataFrame, column: str, key: str) -> DataFrame:
    """Edges with what a table says about one end; the table is read anew for each batch."""
    return stream.join(static, stream[column] == static[key])


def pairs_within(stream: DataFrame, first: str, second: str, span: str = "1 hour", late: str = "1 day") -> DataFrame:
    """(user_id, event_id, after): a user's edges of one type that follow edges of another within ``span``.

    Both sides carry a watermark, so state older than the span is dropped.
    """
    watched = stream.withWatermark("ts", late)
    left = watched.where(F.col("event_type") == first).select("user_id", "event_id", F.col("ts").alias("began"))
    right = watched.where(F.col("event_type") == second).select(F.col("user_id").alias("same_user"), F.col("event_id").alias("after"), F.col("ts").alias("ended"))
    near = F.expr(f"user_id = same_user AND ended >= began AND ended <= began + INTERVAL {span}")
    return left.join(right, near).select("user_id", "event_id", "after")


def run_once(result: DataFrame, name: str, mode: str = "complete") -> DataFrame:
    """Work off all input that is there and give the result as a table in the shared folder.

    A batch that is run again replaces its own files.
    """
    spark = result.sparkSession
    where = fresh_path(spark, f"stream-{name}")

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{where}/rows" if mode == "complete" else f"{where}/rows/batch={number}")

    query = result.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", f"{where}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(result.schema).parquet(f"{where}/rows").select(*result.columns)


def add_edges(closure: DataFrame, base: DataFrame, fresh: DataFrame) -> DataFrame:
    """The closure after new edges: what reaches their starts joins what their ends reach.

    ``base`` holds the edges before; new edges may use each other, so rounds go on
    until nothing is added.
    """
    closure = checkpointed(closure)
    delta = checkpointed(m.minus(fresh, base))
    while not delta.isEmpty():
        left = m.union(delta, m.product(closure, delta))
        both = m.union(left, m.product(left, closure))
        both = m.union(both, m.product(both, both))
        delta = checkpointed(m.minus(both, closure))
        closure = checkpointed(m.union(closure, delta))
    return closure

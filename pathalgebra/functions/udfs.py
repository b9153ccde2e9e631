"""Functions for SQL users: path checks, tokens, z-order, and path views."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import Row

from pathalgebra.operators.quadtree import interleave
from pathalgebra.plans.evaluate import answer
from pathalgebra.plans.paths import _TOKEN, parse_path
from pathalgebra.sources.graphs import Graph


def path_is_valid(text: pd.Series) -> pd.Series:
    def check(x: str | None) -> bool:
        try:
            parse_path(x or "")
        except ValueError:
            return False
        return True

    return text.map(check)


class PathTokens:
    """Table function: the tokens of a path, one row each."""

    def eval(self, text: str):
        at = 0
        while text and at < len(text.rstrip()):
            m = _TOKEN.match(text, at)
            if not m:
                return
            yield Row(token=m[1])
            at = m.end()


def zorder_udf(r: pd.Series, c: pd.Series) -> pd.Series:
    return pd.Series(interleave(r.to_numpy(), c.to_numpy()).astype("int64"))


class Quadrants:
    """Table function: depth and z-order code of every quadrant on the way to a cell."""

    def eval(self, r: int, c: int, levels: int):
        code = 0
        for k in range(levels - 1, -1, -1):
            code = code * 4 + (r >> k & 1) * 2 + (c >> k & 1)
            yield Row(depth=levels - k, code=code)


def register(spark: SparkSession) -> None:
    spark.udf.register("path_is_valid", F.pandas_udf(path_is_valid, "boolean"))
    spark.udf.register("zorder_udf", F.pandas_udf(zorder_udf, "long"))
    spark.udtf.register("quadrants", F.udtf(Quadrants, returnType="depth long, code long"))
    spark.udtf.register("path_tokens", F.udtf(PathTokens, returnType="token string"))


def create_path_view(spark: SparkSession, name: str, graph: Graph, query: str, **options) -> DataFrame:
    """A temporary view of a query's answers, for use in SQL."""
    df = answer(graph, query, **options)
    df.createOrReplaceTempView(name)
    return df

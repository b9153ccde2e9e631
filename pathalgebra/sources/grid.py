"""A data source for the generated grid: uniform random matrices without input files."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Cells(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class _GridReader(DataSourceReader):
    def __init__(self, options: dict):
        self.density, self.seed = float(options.get("density", "0.01")), int(options.get("seed", "0"))
        self.side, self.parts = int(options.get("side", "1000")), int(options.get("partitions", "4"))

    def partitions(self) -> list[_Cells]:
        cells = self.side * self.side
        step = -(-cells // self.parts)
        return [_Cells(at, min(at + step, cells)) for at in range(0, cells, step)]

    def read(self, partition: _Cells) -> Iterator[pa.RecordBatch]:
        prime = 2**31 - 1
        for at in range(partition.first, partition.last, 1 << 20):
            cell = np.arange(at, min(at + (1 << 20), partition.last), dtype=np.int64)
            # The same numbers as sources.graphs.uniform; no product leaves 64 bits.
            h = (48271 * cell + 1 + 1_000_003 * self.seed) % prime
            h = h * h % prime
            h = (h + 7919 * self.seed + cell) % prime
            ones = cell[h * h % prime < int(self.density * prime)]
            yield pa.RecordBatch.from_arrays([pa.array(ones // self.side), pa.array(ones % self.side)], names=["r", "c"])


class GridSource(DataSource):
    """``spark.read.format("uniform_grid")`` with options density, seed, side and partitions."""

    @classmethod
    def name(cls) -> str:
        return "uniform_grid"

    def schema(self) -> str:
        return "r long, c long"

    def reader(self, schema) -> _GridReader:
        return _GridReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(GridSource)

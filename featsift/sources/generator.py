"""A data source of synthetic sparse rows, for scale tests: spark.read.format("sparse_rows")."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Range(InputPartition):
    def __init__(self, start: int, stop: int):
        self.start, self.stop = start, stop


class SparseRows(DataSource):
    """Options: rows, features, nonzeros (per row), partitions, seed.  Feature numbers follow a Zipf-like law; the label depends on the lowest ones."""

    @classmethod
    def name(cls) -> str:
        return "sparse_rows"

    def schema(self) -> str:
        return "row_id long, y int, features array<long>"

    def reader(self, schema) -> DataSourceReader:
        return SparseRowsReader({k.lower(): int(v) for k, v in self.options.items() if str(v).isdigit()})


class SparseRowsReader(DataSourceReader):
    def __init__(self, options: dict[str, int]):
        self.rows, self.features = options.get("rows", 1000), options.get("features", 10_000)
        self.nonzeros, self.parts, self.seed = options.get("nonzeros", 20), options.get("partitions", 4), options.get("seed", 7)

    def partitions(self) -> list[InputPartition]:
        edges = np.linspace(0, self.rows, self.parts + 1).astype(int)
        return [_Range(int(a), int(b)) for a, b in zip(edges, edges[1:])]

    def read(self, partition: _Range) -> Iterator[tuple]:
        for row in range(partition.start, partition.stop):
            rng = np.random.default_rng((self.seed, row))
            found = np.unique((self.features ** rng.random(self.nonzeros)).astype(np.int64) - 1)
            y = int((found < 8).sum() % 2)
            yield row, y, found.tolist()


def register(spark: SparkSession) -> None:
    spark.dataSource.register(SparseRows)

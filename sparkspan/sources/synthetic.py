"""A Python data source of synthetic point sets, made in parallel from a seed."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Range(InputPartition):
    def __init__(self, first: int, last: int):
        super().__init__((first, last))
        self.first, self.last = first, last


class PointsSource(DataSource):
    """Options: kind (uniform, normal or varied), n, d, seed, partitions. varied draws cluster centres
    and gives each its own spread."""

    @classmethod
    def name(cls) -> str:
        return "points"

    def schema(self) -> str:
        return "pid bigint, " + ", ".join(f"x{i} bigint" for i in range(int(self.options.get("d", 2))))

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.kind, self.n, self.d = options.get("kind", "uniform"), int(options.get("n", 1000)), int(options.get("d", 2))
        self.seed, self.parts = int(options.get("seed", 0)), int(options.get("partitions", 4))

    def partitions(self):
        edges = [self.n * i // self.parts for i in range(self.parts + 1)]
        return [_Range(a, b) for a, b in zip(edges, edges[1:])]

    def read(self, part):
        import numpy as np
        import pyarrow as pa

        rng = np.random.default_rng([self.seed, part.first])
        k = part.last - part.first
        if self.kind == "uniform":
            x = rng.random((k, self.d)) - 0.5
        elif self.kind == "normal":
            x = rng.standard_normal((k, self.d))
        else:
            shared = np.random.default_rng(self.seed)
            centres, widths = shared.random((20, self.d)), 10.0 ** shared.uniform(-3, -1, 20)
            c = rng.integers(0, 20, k)
            x = centres[c] + rng.standard_normal((k, self.d)) * widths[c][:, None]
        cols = [np.arange(part.first, part.last)] + list(np.rint(x * 1e6).astype(np.int64).T)
        yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=["pid"] + [f"x{i}" for i in range(self.d)])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(PointsSource)

"""A data source for generated meshes: ``spark.read.format("gridmesh")``."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class GridMesh(DataSource):
    """Options: n (spans per axis), degree, dim, parts. Rows (v, ix): ids and multi-indices of the splines."""

    @classmethod
    def name(cls) -> str:
        return "gridmesh"

    def schema(self) -> str:
        return "v bigint, ix array<int>"

    def reader(self, schema) -> DataSourceReader:
        return _Reader({k.lower(): v for k, v in self.options.items()})


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.size = int(options.get("n", 4)) + int(options.get("degree", 1))
        self.dim = int(options.get("dim", 3))
        self.parts = int(options.get("parts", 4))

    def partitions(self) -> list[InputPartition]:
        total = self.size**self.dim
        cut = [total * i // self.parts for i in range(self.parts + 1)]
        return [InputPartition((a, b)) for a, b in zip(cut, cut[1:], strict=False) if b > a]

    def read(self, partition):
        a, b = partition.value
        for v in range(a, b):
            yield v, [v // self.size**k % self.size for k in range(self.dim)]


def register(spark: SparkSession) -> None:
    spark.dataSource.register(GridMesh)

"""Parameter grids as a data source: ``spark.read.format("paramgrid").option("estimate", "0.1,0.2")...``"""

from __future__ import annotations

import itertools

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class ParameterGrid(DataSource):
    """Every combination of the options' comma-separated numbers, a column of doubles each, in order of their names."""

    @classmethod
    def name(cls) -> str:
        return "paramgrid"

    def axes(self) -> dict[str, list[float]]:
        return {k: [float(x) for x in v.split(",")] for k, v in sorted(self.options.items()) if k not in ("path", "partitions")}

    def schema(self) -> str:
        return ", ".join(f"`{k}` double" for k in self.axes())

    def reader(self, schema) -> DataSourceReader:
        return _Reader(list(self.axes().values()), int(self.options.get("partitions", "1")))


class _Reader(DataSourceReader):
    def __init__(self, values: list[list[float]], parts: int):
        self.values, self.parts = values, parts

    def partitions(self):
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition):
        for i, row in enumerate(itertools.product(*self.values)):
            if i % self.parts == partition.value:
                yield tuple(row)


def grid(spark: SparkSession, partitions: int = 1, **axes) -> DataFrame:
    spark.dataSource.register(ParameterGrid)
    reader = spark.read.format("paramgrid").option("partitions", str(partitions))
    for name, values in axes.items():
        reader = reader.option(name, ",".join(repr(float(v)) for v in values))
    return reader.load()

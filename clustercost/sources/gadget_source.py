"""A Python data source that emits the disjointness gadget: ``spark.read.format('disjointness_gadget')``."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class GadgetSource(DataSource):
    """Options: ``x`` and ``y``, equal strings of 0 and 1; ``parts``, how many tasks to read by."""

    @classmethod
    def name(cls) -> str:
        return "disjointness_gadget"

    def schema(self) -> str:
        return "id bigint, kind string, x double, y double"

    def reader(self, schema) -> DataSourceReader:
        return GadgetReader(self.options)


class GadgetReader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.x, self.y, self.parts = options.get("x", ""), options.get("y", ""), int(options.get("parts", 2))
        if len(self.x) != len(self.y):
            raise ValueError("x and y have different lengths")

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        for i in range(partition.value, len(self.x), self.parts):
            bx, by, place = int(self.x[i]), int(self.y[i]), i + 1
            for kind, offset, height in (("a", 0, bx), ("p", 1, bx - 1), ("b", 2, 3 - by), ("q", 3, 4 - by)):
                yield place * 4 + offset, kind, float(2 * place), float(height)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(GadgetSource)

"""A user-defined data source with partitions: numbers 0 .. rows - 1."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from gridmin.session import ship


class Slice(InputPartition):
    def __init__(self, start: int, end: int):
        self.start, self.end = start, end


class Counter(DataSource):
    @classmethod
    def name(cls) -> str:
        return "gridmin_counter"

    def schema(self) -> str:
        return "i bigint"

    def reader(self, schema) -> "CounterReader":
        return CounterReader(int(self.options.get("rows", "0")), int(self.options.get("parts", "1")))


class CounterReader(DataSourceReader):
    def __init__(self, rows: int, parts: int):
        self.rows, self.parts = rows, parts

    def partitions(self) -> list[Slice]:
        return [Slice(self.rows * k // self.parts, self.rows * (k + 1) // self.parts) for k in range(self.parts)]

    def read(self, part: Slice) -> Iterator[tuple]:
        for i in range(part.start, part.end):
            yield (i,)


def register_counter(spark: SparkSession) -> None:
    ship(spark)
    spark.dataSource.register(Counter)

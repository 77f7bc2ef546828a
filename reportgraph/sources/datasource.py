"""Rendered reports as a data source: ``spark.read.format("reports").option("rows", n).load()``."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "report_id long, title string, description string"


class _Range(InputPartition):
    def __init__(self, start: int, stop: int):
        super().__init__((start, stop))
        self.start, self.stop = start, stop


class _Reader(DataSourceReader):
    """Reports that are a function of their number, so partitions can be read again anywhere."""

    def __init__(self, rows: int, parts: int):
        self.rows, self.parts = rows, max(1, parts)

    def partitions(self) -> list[_Range]:
        step = -(-self.rows // self.parts) if self.rows else 0
        return [_Range(a, min(self.rows, a + step)) for a in range(0, self.rows, step)] if step else [_Range(0, 0)]

    def read(self, partition: _Range) -> Iterator[tuple]:
        for k in range(partition.start, partition.stop):
            yield k, f"Label printer offline near dock {k % 5}", f"Dock Number: {k % 5}\nSource Ip: 10.0.{k % 256}.{k % 7}\nprinter at 10.0.{k % 256}.{k % 7} is silent"


class ReportSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "reports"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> _Reader:
        return _Reader(int(self.options.get("rows", "1000")), int(self.options.get("partitions", "4")))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(ReportSource)

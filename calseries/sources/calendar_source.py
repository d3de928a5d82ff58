"""A calendar as a Spark data source: spark.read.format("calendar").option("start", ...).option("seconds", ...)."""

from __future__ import annotations

from datetime import datetime, timedelta

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Part(InputPartition):
    def __init__(self, lo: int, hi: int):
        super().__init__((lo, hi))
        self.lo, self.hi = lo, hi


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.start, self.seconds = datetime.fromisoformat(options["start"]), int(options.get("seconds", 86400))
        self.n, self.parts = int(options["n"]), max(1, int(options.get("parts", 4)))

    def partitions(self):
        cut = [self.n * k // self.parts for k in range(self.parts + 1)]
        return [_Part(a, b) for a, b in zip(cut[:-1], cut[1:], strict=True) if a < b]

    def read(self, partition):
        for i in range(partition.lo, partition.hi):
            yield i, self.start + timedelta(seconds=self.seconds * i)


class CalendarSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "calendar"

    def schema(self) -> str:
        return "idx bigint, t timestamp_ntz"

    def reader(self, schema):
        return _Reader(self.options)


def register(spark: SparkSession) -> None:
    from pyspark import cloudpickle
    import sys

    cloudpickle.register_pickle_by_value(sys.modules[__name__])
    spark.dataSource.register(CalendarSource)

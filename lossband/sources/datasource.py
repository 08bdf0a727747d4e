"""A Python data source that makes planted series, for sessions that read everything by format name."""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Part(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.series, self.length = int(options.get("series", 12)), int(options.get("length", 128))

    def partitions(self):
        return [_Part(a, min(a + 8, self.series)) for a in range(0, self.series, 8)]

    def read(self, partition):
        import math

        for s in range(partition.first, partition.last):
            for t in range(self.length):
                yield (f"planted{s % 4}", str(s), t, round(1000 * (10 + 3 * math.sin(2 * math.pi * t / 16 + s))))


class PlantedSource(DataSource):
    """``spark.dataSource.register(PlantedSource)``, then ``spark.read.format("planted")``."""

    @classmethod
    def name(cls):
        return "planted"

    def schema(self):
        return "source string, series_id string, t long, y long"

    def reader(self, schema):
        return _Reader(self.options)

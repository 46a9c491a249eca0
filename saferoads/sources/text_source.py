"""A Python data source for plain text edge lists: `u w len ess` a line, blank lines and lines from # on are skipped."""

from __future__ import annotations

import glob

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class RoadText(DataSource):
    """spark.read.format("roadtext").load(path pattern); register with spark.dataSource.register(RoadText)."""

    @classmethod
    def name(cls):
        return "roadtext"

    def schema(self):
        return "u bigint, w bigint, len bigint, ess int"

    def reader(self, schema):
        return RoadTextReader(self.options["path"])


class RoadTextReader(DataSourceReader):
    """One partition for each file that the pattern names; the files must be in a folder that all executors share."""

    def __init__(self, pattern: str):
        self.pattern = pattern

    def partitions(self):
        return [InputPartition(path) for path in sorted(glob.glob(self.pattern))]

    def read(self, partition):
        with open(partition.value) as lines:
            for line in lines:
                parts = line.split("#")[0].split()
                if parts:
                    u, w, length, ess = map(int, parts)
                    yield u, w, length, ess

"""A Python data source of synthetic reports: ``spark.read.format("sketch_reports").option("n", ...).load()``."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from .workers import ship


class SketchReports(DataSource):
    """Options ``n, k, m, s, p, seed, items, partitions``: items follow a geometric ladder."""

    @classmethod
    def name(cls) -> str:
        return "sketch_reports"

    def schema(self) -> str:
        return "report_id long, item string, j int, x int"

    def reader(self, schema):
        return _Reader(dict(self.options))


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.o = options

    def partitions(self):
        return [InputPartition(i) for i in range(int(self.o.get("partitions", 4)))]

    def read(self, partition):
        from privsketch.functions.prf import prf_int
        from privsketch.functions.sqlapi import replay_subset

        o = self.o
        n, parts, items, seed = (int(o.get(a, b)) for a, b in (("n", 1000), ("partitions", 4), ("items", 16), ("seed", 42)))
        for report in range(partition.value, n, parts):
            item = f"i{prf_int(seed, 'item', report) % items}"
            j, cells = replay_subset(seed, int(o.get("k", 8)), int(o.get("m", 64)), int(o.get("s", 5)), float(o.get("p", 0.6)), report, item)
            for x in cells:
                yield report, item, j, x


def register(spark: SparkSession) -> None:
    ship(spark).dataSource.register(SketchReports)

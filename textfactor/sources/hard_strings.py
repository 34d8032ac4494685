"""A Python data source for the hard input families: spark.read.format("hard_strings").option("family", ...).option("n", ...).load()."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from textfactor.kernels import hard

SCHEMA = "case_no int, ones int, text string"


class HardStrings(DataSource):
    """family: single_one (one string per place of the one, and one without) or threshold (a 1 every `period` places)."""

    @classmethod
    def name(cls) -> str:
        return "hard_strings"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return HardStringsReader(self.options)


class HardStringsReader(DataSourceReader):
    def __init__(self, options):
        self.family, self.n, self.parts = options.get("family", "single_one"), int(options.get("n", "16")), int(options.get("partitions", "2"))

    def partitions(self):
        return [InputPartition(k) for k in range(self.parts)]

    def read(self, partition):
        for case in range(partition.value, self.n + 1, self.parts):
            if self.family == "single_one":
                yield case, int(case < self.n), hard.single_one(self.n, case if case < self.n else None)
            else:
                text = "".join("1" if case and p % case == 0 else "0" for p in range(self.n))
                yield case, text.count("1"), text


def register(spark: SparkSession) -> None:
    spark.dataSource.register(HardStrings)

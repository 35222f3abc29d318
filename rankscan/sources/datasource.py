"""``spark.read.format("null_law")``: the exact law as a data source with options n and w_max, a partition per width."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from rankscan.functions import nulllaw as N


class NullLawSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "null_law"

    def schema(self) -> str:
        return "n int, w int, phi bigint, ways string"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(int(self.options["n"]), int(self.options["w_max"]))


class _Reader(DataSourceReader):
    def __init__(self, n: int, w_max: int):
        self.n, self.w_max = n, w_max

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(w) for w in range(1, min(self.w_max, self.n) + 1)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        w = partition.value
        for k, ways in enumerate(N.law_by_product(self.n, w)):
            yield self.n, w, k + N.least_sum(w), str(ways)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(NullLawSource)

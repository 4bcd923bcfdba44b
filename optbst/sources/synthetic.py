"""A data source of made weights: spark.read.format("synthetic_weights").option("n", 1000).option("law", "zipf").load().

Rows (idx, hit, miss), idx 0..n, as every solver takes them. Integers by rule, so the same options give the same
rows everywhere. Laws: ``uniform`` and ``zipf`` for both weights, ``all_hit`` without misses, ``all_miss`` without hits.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Rows(InputPartition):
    def __init__(self, first: int, end: int):
        super().__init__((first, end))
        self.first, self.end = first, end


class _Reader(DataSourceReader):
    def __init__(self, options: dict[str, str]):
        self.n, self.seed, self.law = int(options.get("n", 100)), int(options.get("seed", 0)), options.get("law", "uniform")
        if self.n < 0 or self.law not in ("uniform", "zipf", "all_hit", "all_miss"):
            raise ValueError("n must not be negative; law is uniform, zipf, all_hit or all_miss")

    def partitions(self) -> list[InputPartition]:
        return [_Rows(at, min(at + 100_000, self.n + 1)) for at in range(0, self.n + 1, 100_000)]

    def read(self, partition: InputPartition) -> Iterator[tuple[int, int, int]]:
        for i in range(partition.first, partition.end):
            draw = (i * 7919 + self.seed * 104729) % 1009
            weight = 1_000_000 // (draw + 1) if self.law == "zipf" else draw + 1
            other = 1_000_000 // ((draw * 31 + 7) % 1009 + 1) if self.law == "zipf" else (draw * 31 + 7) % 1009 + 1
            yield i, 0 if i == 0 or self.law == "all_miss" else weight, 0 if self.law == "all_hit" else other


class SyntheticWeights(DataSource):
    """The data source ``synthetic_weights``."""

    @classmethod
    def name(cls) -> str:
        return "synthetic_weights"

    def schema(self) -> str:
        return "idx bigint, hit bigint, miss bigint"

    def reader(self, schema) -> DataSourceReader:  # noqa: ANN001
        return _Reader(dict(self.options))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(SyntheticWeights)

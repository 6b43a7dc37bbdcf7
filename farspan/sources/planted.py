"""A data source of synthetic windows with or without a far link, of any size: spark.read.format('planted')."""

from __future__ import annotations

import hashlib

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Range(InputPartition):
    def __init__(self, low: int, high: int):
        self.low, self.high = low, high


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.rows, self.length = int(options.get("rows", 100)), int(options.get("length", 128))
        self.seed, self.parts = options.get("seed", "7"), int(options.get("partitions", 4))

    def partitions(self):
        step = -(-self.rows // self.parts)
        return [_Range(a, min(self.rows, a + step)) for a in range(0, self.rows, max(1, step))]

    def read(self, partition):
        for i in range(partition.low, partition.high):
            word = lambda j, who=i // 2: "w" + hashlib.md5(f"{self.seed}:{who}:{j}".encode()).hexdigest()[:6]
            toks = [word(j) for j in range(self.length)]
            quarter = self.length // 4
            toks[-quarter:] = toks[:quarter] if i % 2 else [word(j, -1 - i) for j in range(quarter)]
            yield (i, "planted", 0, self.length, i % 2, toks)


class PlantedSource(DataSource):
    """Options: rows, length, seed, partitions.  Odd rows repeat their first quarter as their last."""

    @classmethod
    def name(cls) -> str:
        return "planted"

    def schema(self) -> str:
        return "doc_id bigint, category string, start bigint, len int, label int, toks array<string>"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(dict(self.options))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(PlantedSource)

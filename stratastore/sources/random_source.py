"""A Python data source of random contents: spark.read.format('random_contents') with options seed, n, count."""

from __future__ import annotations

import hashlib

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def random_body(seed: int, n: int) -> bytes:
    return b"".join(hashlib.sha256(f"{seed}:{i}".encode()).digest() for i in range(-(-n // 32)))[:n]


class RandomContents(DataSource):
    @classmethod
    def name(cls) -> str:
        return "random_contents"

    def schema(self) -> str:
        return "content_id string, series string, version bigint, body binary, n bigint"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(*(int(self.options.get(k, d)) for k, d in (("seed", 0), ("n", 4096), ("count", 1))))


class _Reader(DataSourceReader):
    STEP = 64

    def __init__(self, seed: int, n: int, count: int):
        self.seed, self.n, self.count = seed, n, count

    def partitions(self):
        return [InputPartition(a) for a in range(0, self.count, self.STEP)] or [InputPartition(0)]

    def read(self, partition):
        for k in range(partition.value, min(partition.value + self.STEP, self.count)):
            seed = self.seed + k
            yield (f"random:{seed}", "random", seed, random_body(seed, self.n), self.n)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(RandomContents)

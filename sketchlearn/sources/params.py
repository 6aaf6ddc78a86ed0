"""Parameters of a hash family as a table source: spark.read.format("hash_params").option("k", 64).load()."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions.hashing import PRIME, seeded

#: Rows of a partition.
ROWS = 100_000


class HashParams(DataSource):
    """(j, c1, c2) of a two-universal family. Options: k (needed), seed (7), p (2^31 - 1). Rows are made where they are read; nothing is stored."""

    @classmethod
    def name(cls) -> str:
        return "hash_params"

    def schema(self) -> str:
        return "j int, c1 bigint, c2 bigint"

    def reader(self, schema) -> DataSourceReader:
        if "k" not in self.options:
            raise ValueError("hash_params needs the option k")
        return HashParamsReader(int(self.options["k"]), int(self.options.get("seed", 7)), int(self.options.get("p", PRIME)))


class HashParamsReader(DataSourceReader):
    def __init__(self, k: int, seed: int, p: int):
        self.k, self.seed, self.p = k, seed, p

    def partitions(self) -> list[InputPartition]:
        return [InputPartition((i, min(self.k, i + ROWS))) for i in range(0, self.k, ROWS)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        for j in range(*partition.value):
            yield j, seeded(self.seed, "c1", j) % self.p, 1 + seeded(self.seed, "c2", j) % (self.p - 1)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(HashParams)


def read(spark: SparkSession, k: int, seed: int = 7):
    register(spark)
    return spark.read.format("hash_params").option("k", k).option("seed", seed).load()

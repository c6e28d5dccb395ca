"""`spark.read.format("zipf_items")`: rank-numbered Zipf ids made in parallel, for load tests of any size."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class ZipfItems(DataSource):
    """Options: s (above 1), n_ids, rows, parts, seed. Columns rid, item, key."""

    @classmethod
    def name(cls) -> str:
        return "zipf_items"

    def schema(self) -> str:
        return "rid string, item bigint, key bigint"

    def reader(self, schema):
        return ZipfReader(dict(self.options))


class ZipfReader(DataSourceReader):
    def __init__(self, options: dict):
        take = lambda name, kind, default: kind(options.get(name, default))
        self.s, self.n_ids, self.rows = take("s", float, 1.1), take("n_ids", int, 2_000_000), take("rows", int, 100_000)
        self.parts, self.seed = take("parts", int, 8), take("seed", int, 7)
        if self.s <= 1:
            raise ValueError("s must be above 1")

    def partitions(self):
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition):
        import numpy as np
        import pyarrow as pa

        low, high = (self.rows * (partition.value + i) // self.parts for i in (0, 1))
        rng = np.random.default_rng([self.seed, partition.value])
        for at in range(low, high, 100_000):
            ids = np.arange(at, min(high, at + 100_000))
            u = rng.random(len(ids))
            item = np.floor((1 - u * (1 - self.n_ids ** (1 - self.s))) ** (-1 / (self.s - 1))).astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(ids.astype(str)), pa.array(item), pa.array(item % 2147483647)], ["rid", "item", "key"])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(ZipfItems)

"""A partitioned Python data source of skewed synthetic microdata: ``spark.read.format("microdata")``."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Part(InputPartition):
    def __init__(self, index: int, first: int, last: int):
        self.index, self.first, self.last = index, first, last


class _Reader(DataSourceReader):
    def __init__(self, options: dict[str, str]):
        self.rows, self.domain = int(options.get("rows", 1000)), int(options.get("domain", 50))
        self.skew, self.parts, self.seed = float(options.get("skew", 1.0)), int(options.get("parts", 4)), int(options.get("seed", 1))

    def partitions(self) -> list[_Part]:
        cut = [self.rows * i // self.parts for i in range(self.parts + 1)]
        return [_Part(i, a, b) for i, (a, b) in enumerate(zip(cut, cut[1:], strict=False))]

    def read(self, partition: _Part) -> Iterator[pa.RecordBatch]:
        import numpy as np

        weight = 1.0 / np.arange(1, self.domain + 1) ** self.skew
        rng = np.random.default_rng([self.seed, partition.index])
        for at in range(partition.first, partition.last, 65_536):
            n = min(65_536, partition.last - at)
            columns = [np.arange(at, at + n), *rng.integers(0, 10, (3, n)).astype(np.int32), rng.choice(self.domain, n, p=weight / weight.sum()).astype(np.int32)]
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["id", "q0", "q1", "q2", "v"])


class MicrodataSource(DataSource):
    """Options: rows, domain, skew (Zipf exponent), parts, seed."""

    @classmethod
    def name(cls) -> str:
        return "microdata"

    def schema(self) -> str:
        return "id bigint, q0 int, q1 int, q2 int, v int"

    def reader(self, schema) -> _Reader:
        return _Reader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(MicrodataSource)

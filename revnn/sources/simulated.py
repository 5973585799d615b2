"""A Python data source of simulated points: spark.read.format("revnn_uniform").option("n", ...).load()."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

BATCH = 65_536


class Range(InputPartition):
    def __init__(self, first: int, last: int):
        super().__init__((first, last))
        self.first, self.last = first, last


class UniformReader(DataSourceReader):
    """Points first <= id < last of each partition; a point depends on its id and the seed alone."""

    def __init__(self, options):
        self.n, self.seed, self.parts = int(options.get("n", 1000)), int(options.get("seed", 0)), int(options.get("partitions", 8))

    def partitions(self) -> list[Range]:
        cuts = [self.n * i // self.parts for i in range(self.parts + 1)]
        return [Range(a, b) for a, b in zip(cuts, cuts[1:], strict=False) if b > a]

    def read(self, partition: Range) -> Iterator[pa.RecordBatch]:
        for first in range(partition.first, partition.last, BATCH):
            ids = range(first, min(first + BATCH, partition.last))
            keys = (hashlib.md5(f"{i}:{self.seed}".encode() if self.seed else str(i).encode()).digest() for i in ids)
            unit = np.frombuffer(b"".join(k[:8] for k in keys), ">u4").reshape(-1, 2) / 4294967296.0
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(unit[:, 0]), pa.array(unit[:, 1])], names=["id", "x", "y"])


class UniformSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "revnn_uniform"

    def schema(self) -> str:
        return "id long, x double, y double"

    def reader(self, schema) -> UniformReader:
        return UniformReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(UniformSource)

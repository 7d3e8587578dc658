"""A source of synthetic matrices with a given condition number: spark.read.format("dial_matrix")."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Part(InputPartition):
    def __init__(self, number: int, start: int, end: int) -> None:
        self.number, self.start, self.end = number, start, end


class DialReader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.rows, self.n = int(options.get("rows", 1000)), int(options.get("columns", 4))
        self.cond, self.parts = float(options.get("cond", 1.0)), int(options.get("partitions", 4))
        self.seed = int(options.get("seed", 1))

    def partitions(self) -> list[InputPartition]:
        cuts = np.linspace(0, self.rows, self.parts + 1).astype(int)
        return [_Part(k, int(a), int(b)) for k, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)) if b > a]

    def read(self, partition: _Part) -> Iterator[pa.RecordBatch]:
        """Normal rows, whose columns are scaled from 1 to 1/cond and then turned."""
        rng = np.random.default_rng([self.seed, partition.number])
        turn = np.linalg.qr(np.random.default_rng(self.seed).standard_normal((self.n, self.n)))[0]
        scale = np.logspace(0, -np.log10(self.cond), self.n) if self.n > 1 else np.ones(1)
        a = rng.standard_normal((partition.end - partition.start, self.n)) * scale @ turn
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(partition.start, partition.end)), pa.array(list(a), pa.list_(pa.float64()))], names=["id", "a"])


class DialMatrix(DataSource):
    @classmethod
    def name(cls) -> str:
        return "dial_matrix"

    def schema(self) -> str:
        return "id bigint, a array<double>"

    def reader(self, schema) -> DialReader:
        return DialReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(DialMatrix)

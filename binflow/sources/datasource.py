"""Generated scale-free edges as a Python data source: ``spark.read.format("binflow_rmat")``.

Options: scale, degree (16), seed (42), splits (8). Each split makes its own draws in numpy, with
the arithmetic of ``generators.rmat``; loops and repeats are left in.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from binflow.sources.generators import PRIME, QUADRANTS
from binflow.storage import ship_package

DRAWS_AT_ONCE = 1 << 16


class Draws(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class RmatReader(DataSourceReader):
    def __init__(self, scale: int, degree: int, seed: int, splits: int):
        self.scale, self.degree, self.seed, self.splits = scale, degree, seed, splits

    def partitions(self) -> list[Draws]:
        total = self.degree << self.scale
        cuts = [total * i // self.splits for i in range(self.splits + 1)]
        return [Draws(a, b) for a, b in zip(cuts, cuts[1:], strict=False) if b > a]

    def read(self, partition: Draws) -> Iterator[pa.RecordBatch]:
        a, b, c, _ = QUADRANTS
        for at in range(partition.first, partition.last, DRAWS_AT_ONCE):
            ids = np.arange(at, min(at + DRAWS_AT_ONCE, partition.last), dtype=np.int64)
            src, dst = np.zeros(len(ids), np.int64), np.zeros(len(ids), np.int64)
            for level in range(self.scale):
                x = (ids % PRIME * 48271 + (level + 1) * 69621 + self.seed) % PRIME
                for k in range(3):
                    x = (x * x + x * (16807 + level) + 12345 + k) % PRIME
                u = x / float(PRIME)
                src = src * 2 + (u >= a + b)
                dst = dst * 2 + (((u >= a) & (u < a + b)) | (u >= a + b + c))
            yield pa.RecordBatch.from_arrays([pa.array(src), pa.array(dst)], ["src", "dst"])


class RmatSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "binflow_rmat"

    def schema(self) -> str:
        return "src bigint, dst bigint"

    def reader(self, schema) -> RmatReader:
        return RmatReader(int(self.options["scale"]), *(int(self.options.get(k, d)) for k, d in (("degree", 16), ("seed", 42), ("splits", 8))))


def register(spark: SparkSession) -> None:
    ship_package(spark)
    spark.dataSource.register(RmatSource)

"""A data source of synthetic worker gradients: ``spark.read.format("synthetic_gradient")``."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Worker(InputPartition):
    def __init__(self, worker: int):
        super().__init__(worker)
        self.worker = worker


class _GradientReader(DataSourceReader):
    def __init__(self, options):
        self.d, self.workers = int(options.get("d", 1000)), int(options.get("workers", 4))
        self.skew, self.seed = float(options.get("skew", 1.0)), int(options.get("seed", 1))

    def partitions(self):
        return [_Worker(w) for w in range(self.workers)]

    def read(self, partition: _Worker) -> Iterator[pa.RecordBatch]:
        rng = np.random.default_rng([self.seed, partition.worker])
        for start in range(0, self.d, 65_536):
            coord = np.arange(start, min(self.d, start + 65_536))
            val = rng.standard_normal(len(coord)) / (1.0 + coord) ** self.skew
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(coord), partition.worker, np.int32)), pa.array(coord), pa.array(val)], names=["worker", "coord", "val"])


class SyntheticGradient(DataSource):
    """Options d, workers, skew (power of the decay along coordinates) and seed; one partition a worker."""

    @classmethod
    def name(cls) -> str:
        return "synthetic_gradient"

    def schema(self) -> str:
        return "worker int, coord long, val double"

    def reader(self, schema) -> DataSourceReader:
        return _GradientReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(SyntheticGradient)

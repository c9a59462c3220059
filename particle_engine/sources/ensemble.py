"""Python data source ``ensemble_state``: hashed start states, one partition per range of particles, read as Arrow batches.

Options: particles, cells, seed, partitions.  The same numbers as ``init_ensemble``;
it stands for readers of a model's own state formats, which plug in at ``read``.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from particle_engine.functions.rng import py_uniform

BATCH = 4096


class ParticleRange(InputPartition):
    def __init__(self, low: int, high: int):
        self.low, self.high = low, high


class EnsembleReader(DataSourceReader):
    def __init__(self, options: dict):
        self.particles, self.cells = int(options.get("particles", 16)), int(options.get("cells", 80))
        self.seed, self.n = int(options.get("seed", 42)), int(options.get("partitions", 4))

    def partitions(self) -> list[InputPartition]:
        cuts = [k * self.particles // self.n for k in range(self.n + 1)]
        return [ParticleRange(a, b) for a, b in zip(cuts, cuts[1:]) if a < b]

    def read(self, partition: ParticleRange) -> Iterator[pa.RecordBatch]:
        keys = [(p, c) for p in range(partition.low, partition.high) for c in range(self.cells)]
        for i in range(0, len(keys), BATCH):
            part = keys[i : i + BATCH]
            columns = [pa.array([p for p, _ in part], pa.int64()), pa.array([c for _, c in part], pa.int32()), pa.array([py_uniform(self.seed, 0, p, c) for p, c in part], pa.float64())]
            yield pa.RecordBatch.from_arrays(columns, ["particle_id", "cell_id", "x"])


class EnsembleSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "ensemble_state"

    def schema(self) -> str:
        return "particle_id long, cell_id int, x double"

    def reader(self, schema) -> EnsembleReader:
        return EnsembleReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(EnsembleSource)

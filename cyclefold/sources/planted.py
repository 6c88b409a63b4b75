"""A batch data source of planted videos: ``spark.read.format("planted").option("scene", 2)``."""

from __future__ import annotations

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..plans import corrupt, synth


class PlantedSource(DataSource):
    """Options: scene, cycles, frames, height, width, videos, corruption, level, seed."""

    @classmethod
    def name(cls) -> str:
        return "planted"

    def schema(self) -> str:
        return "video_id string, t int, h int, w int, ch int, px array<float>, phi double"

    def reader(self, schema) -> DataSourceReader:
        return PlantedReader(dict(self.options))


class PlantedReader(DataSourceReader):
    def __init__(self, options: dict):
        self.options = options

    def _int(self, name: str, default: int) -> int:
        return int(self.options.get(name, default))

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(k) for k in range(self._int("videos", 1))]

    def read(self, partition: InputPartition):
        k = partition.value
        n, h, w = self._int("frames", 600), self._int("height", 32), self._int("width", 32)
        cycles = float(self.options.get("cycles", 15))
        basis = np.random.default_rng(self._int("seed", 42)).normal(0, 0.125, (9, 64))
        px = synth.frames_of(basis, self._int("scene", 1), cycles, n, h, w)
        px = corrupt.apply(px, h, w, self.options.get("corruption", "none"), float(self.options.get("level", 0)), f"{k}|{self._int('seed', 42)}")
        for t in range(n):
            yield str(k), t, h, w, 1, px[t].astype(float).tolist(), float(2 * np.pi * cycles * t / n % (2 * np.pi))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(PlantedSource)

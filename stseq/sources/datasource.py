"""A Python data source ``planted`` (spark.read.format): the generator with NumPy, one partition for each pattern."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class PatternPartition(InputPartition):
    def __init__(self, pattern: int):
        self.pattern = pattern


class PlantedReader(DataSourceReader):
    def __init__(self, options: dict):
        self.o = {k.lower(): v for k, v in options.items()}

    def _get(self, name: str, default: float) -> float:
        return float(self.o.get(name.lower(), default))

    def partitions(self) -> list[InputPartition]:
        return [PatternPartition(p) for p in range(int(self._get("Pn", 10)))]

    def read(self, partition: PatternPartition) -> Iterator[tuple]:
        ps, ni, nf = int(self._get("Ps", 5)), int(self._get("Ni", 100)), int(self._get("Nf", 20))
        d, t, r, span = self._get("DSize", 1000), self._get("TSize", 1200), self._get("R", 10), self._get("T", 10)
        rng = np.random.default_rng([int(self._get("seed", 0)), partition.pattern])
        base = partition.pattern * 2 * ps * ni
        types = rng.integers(0, nf, ps)
        x = np.stack([rng.random(ni) * d, rng.random(ni) * d, rng.random(ni) * t], axis=1)
        for k in range(ps):
            if k:
                x = x[rng.integers(0, ni, ni)]
                rho, phi = r * np.sqrt(rng.random(ni)), 2 * np.pi * rng.random(ni)
                x = x + np.stack([rho * np.cos(phi), rho * np.sin(phi), (1 - rng.random(ni)) * np.minimum(span, t - x[:, 2])], axis=1)
                x[:, :2] = np.where(x[:, :2] < 0, -x[:, :2], np.where(x[:, :2] > d, 2 * d - x[:, :2], x[:, :2]))
            for i, row in enumerate(x):
                yield (base + k * ni + i, f"f{types[k]:02d}", *map(float, row))
        noise = rng.random((ps * ni, 3)) * [d, d, t]
        for i, (row, f) in enumerate(zip(noise, rng.integers(0, nf, ps * ni))):
            yield (base + ps * ni + i, f"f{f:02d}", *map(float, row))


class PlantedDataSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "planted"

    def schema(self) -> str:
        return "id bigint, type string, x double, y double, t double"

    def reader(self, schema) -> DataSourceReader:
        return PlantedReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(PlantedDataSource)

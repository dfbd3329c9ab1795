"""Planted clusters: rings and blobs made by formula, and a data source that reads them in batch or as a stream."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader


def _rows(shape: str, begin: int, end: int, k: int, d: int, noise: float, seed: int) -> Iterator[tuple[int, list[float], str]]:
    centres = np.random.default_rng(seed).normal(0, 4, (k, d))
    for i in range(begin, end):
        rng = np.random.default_rng((seed, i))  # a row's numbers follow from its id, whatever partition makes it
        c = i % k
        if shape == "rings":
            radius, angle = 1 + 3 * c + rng.normal(0, noise), rng.random() * 2 * np.pi
            x = [float(radius * np.cos(angle)), float(radius * np.sin(angle))]
        else:
            x = (centres[c] + rng.normal(0, noise, d)).tolist()
        yield i, x, str(c)


class _Part(InputPartition):
    def __init__(self, begin: int, end: int):
        self.begin, self.end = begin, end


class PlantedClusters(DataSource):
    """format("planted_clusters"): options shape (rings, blobs), rows, clusters, dimensions, noise, seed, partitions; for streams rowsPerBatch."""

    @classmethod
    def name(cls) -> str:
        return "planted_clusters"

    def schema(self) -> str:
        return "id long, x array<double>, cls string"

    def reader(self, schema):
        return _Reader(self.options)

    def simpleStreamReader(self, schema):
        return _StreamReader(self.options)


def _settings(options) -> tuple:
    shape = options.get("shape", "rings")
    if shape not in ("rings", "blobs"):
        raise ValueError("shape is rings or blobs")
    return shape, int(options.get("clusters", 2)), int(options.get("dimensions", 2)), float(options.get("noise", 0.15)), int(options.get("seed", 0))


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.options = dict(options)

    def partitions(self):
        n, parts = int(self.options.get("rows", 1000)), int(self.options.get("partitions", 4))
        return [_Part(n * i // parts, n * (i + 1) // parts) for i in range(parts)]

    def read(self, partition):
        shape, k, d, noise, seed = _settings(self.options)
        yield from _rows(shape, partition.begin, partition.end, k, d, noise, seed)


class _StreamReader(SimpleDataSourceStreamReader):
    def __init__(self, options):
        self.options = dict(options)

    def initialOffset(self) -> dict:
        return {"id": 0}

    def read(self, start: dict):
        end = min(start["id"] + int(self.options.get("rowsPerBatch", 100)), int(self.options.get("rows", 1000)))
        return self._between(start["id"], end), {"id": end}

    def readBetweenOffsets(self, start: dict, end: dict):
        return self._between(start["id"], end["id"])

    def _between(self, begin: int, end: int):
        shape, k, d, noise, seed = _settings(self.options)
        return iter(list(_rows(shape, begin, end, k, d, noise, seed)))


def planted(spark: SparkSession, shape: str = "rings", rows: int = 1000, **options) -> DataFrame:
    spark.dataSource.register(PlantedClusters)
    return spark.read.format("planted_clusters").options(shape=shape, rows=str(rows), **{k: str(v) for k, v in options.items()}).load()

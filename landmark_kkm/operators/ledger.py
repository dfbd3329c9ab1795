"""What a run costs: seconds of stages, bytes sent to workers, bytes of partial sums, bytes a worker holds."""

from __future__ import annotations

import time
from contextlib import contextmanager
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from landmark_kkm.operators.coefficients import CoefficientBlock


@dataclass
class CostLedger:
    run_id: str = "run"
    rows: list[dict] = field(default_factory=list)

    @contextmanager
    def timed(self, stage: str, **figures):
        began = time.perf_counter()
        row = {"stage": stage, "seconds": 0.0, "broadcast_bytes": 0, "shuffle_bytes": 0, "model_bytes": 0} | figures
        yield row
        row["seconds"] = time.perf_counter() - began
        self.rows.append(row)

    def seconds(self, stage: str) -> float:
        return float(sum(r["seconds"] for r in self.rows if r["stage"] == stage))

    @property
    def embed_s(self) -> float:
        return self.seconds("embed")

    @property
    def cluster_s(self) -> float:
        return self.seconds("cluster")

    @property
    def total_s(self) -> float:
        return self.embed_s + self.cluster_s

    def to_frame(self, spark: SparkSession) -> DataFrame:
        rows = [(self.run_id, r["stage"], float(r["seconds"]), int(r["broadcast_bytes"]), int(r["shuffle_bytes"]), int(r["model_bytes"])) for r in self.rows]
        return spark.createDataFrame(rows, "run_id string, stage string, seconds double, broadcast_bytes long, shuffle_bytes long, model_bytes long")


def embed_bytes(blocks: list[CoefficientBlock], workers: int = 1) -> int:
    """The embedding's only network cost: landmarks and coefficients, once for each worker."""
    return sum(b.nbytes for b in blocks) * workers


def iteration_bytes(partitions: int, k: int, m: int) -> int:
    """At most k rows leave each partition in an iteration: a sum of m numbers, and five numbers besides, 8 bytes each."""
    return partitions * k * (m + 5) * 8


def centroid_bytes(k: int, m: int, workers: int = 1) -> int:
    return k * m * 8 * workers


def exact_bytes(n: int) -> int:
    """The kernel matrix that exact kernel k-means keeps."""
    return n * n * 8

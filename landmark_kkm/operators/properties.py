"""Checks that an embedding family has what the clustering loop relies on, and the norm estimate behind random projections."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from landmark_kkm.functions import columns as C
from landmark_kkm.functions.kernels import Kernel, local_scales
from landmark_kkm.functions.payloads import Dense, from_arrow
from landmark_kkm.operators.coefficients import CoefficientBlock, EmbeddingFamily
from landmark_kkm.operators.landmarks import Landmarks, collect_landmarks, sample_landmarks
from landmark_kkm.operators.measures import discrepancy_report
from landmark_kkm.session import ship


def check_linear(blocks: list[CoefficientBlock], rows: Landmarks, kernel: Kernel) -> float:
    """Largest gap between the mean of embeddings and the embedding of the mean (R times the mean kernel values)."""
    gap = 0.0
    for b in blocks:
        values = kernel.matrix(rows.rows, b.landmarks.rows)
        gap = max(gap, float(np.abs((values @ b.R.T).mean(0) - b.R @ values.mean(0)).max()))
    return gap


def check_kernelized(blocks: list[CoefficientBlock], rows: Landmarks, kernel: Kernel) -> float:
    """Largest gap between embeddings and what the landmark kernel values alone give."""
    return max(float(np.abs(b.apply(rows.rows, kernel) - (b.R @ kernel.matrix(b.landmarks.rows, rows.rows)).T).max()) for b in blocks)


def check_blocks(blocks: list[CoefficientBlock], max_block_bytes: int) -> bool:
    """Blocks have disjoint landmarks, and each fits a worker."""
    ids = np.concatenate([b.landmarks.ids for b in blocks])
    return len(np.unique(ids)) == len(ids) and all(b.nbytes <= max_block_bytes for b in blocks)


def check_discrepancy(blocks: list[CoefficientBlock], rows: Landmarks, kernel: Kernel, discrepancy: str, k: int = 4, beta: float | None = None) -> dict:
    """How well discrepancies of embeddings stand for kernel distances, for a partition of the rows in turn."""
    return discrepancy_report(rows, np.arange(len(rows)) % k, k, blocks, kernel, discrepancy, beta)


def check_family(family: EmbeddingFamily, ds: DataFrame, kernel: Kernel, l: int = 50, k: int = 4, max_block_bytes: int = 1 << 30, seed: int = 42) -> dict:
    """All four checks on a sample of 4 l rows: {linear, kernelized} are gaps, blocks a truth value, discrepancy a report."""
    rows = collect_landmarks(sample_landmarks(ds.select("id", "x"), 4 * l, seed=seed), seed)
    landmarks = Landmarks(rows.ids[:l], rows.rows.take(np.arange(min(l, len(rows)))))
    blocks = family.fit(landmarks, kernel)
    return {
        "linear": check_linear(blocks, rows, kernel),
        "kernelized": check_kernelized(blocks, rows, kernel),
        "blocks": check_blocks(blocks, max_block_bytes),
        "discrepancy": check_discrepancy(blocks, rows, kernel, family.discrepancy, k, family.beta(blocks)),
    }


def reconstruct_pairs(y: DataFrame, pairs: DataFrame) -> DataFrame:
    """(i, j, value): the low-rank kernel of given pairs (i, j), the inner products of their embeddings."""
    a, b = y.select(F.col("id").alias("i"), F.col("y").alias("yi")), y.select(F.col("id").alias("j"), F.col("y").alias("yj"))
    return pairs.select("i", "j").join(a, "i").join(b, "j").select("i", "j", C.dot(F.col("yi"), F.col("yj")).alias("value"))


def stable_norm(ds: DataFrame, p: int, m: int, seed: int = 42) -> DataFrame:
    """(id, norm): the l2 (p = 2) or l1 (p = 1) norm of dense vectors from m random projections.

    Normal draws are 2-stable, and the mean absolute projection is sqrt(2 / pi) of the norm; Cauchy draws are 1-stable, and as their mean diverges the
    median is taken, which is the norm itself."""
    if p not in (1, 2):
        raise ValueError("p is 1 or 2")
    ship(ds.sparkSession)

    def norms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        draws = None
        for batch in batches:
            rows = from_arrow(batch.column("x")).rows
            if draws is None and len(rows):
                rng = np.random.default_rng(seed)
                draws = rng.normal(size=(rows.shape[1], m)) if p == 2 else rng.standard_cauchy((rows.shape[1], m))
            size = np.abs(rows @ draws) if len(rows) else np.zeros((0, m))
            found = np.sqrt(np.pi / 2) * size.mean(1) if p == 2 else np.median(size, axis=1) if len(rows) else np.zeros(0)
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(found)], names=["id", "norm"])

    return ds.select("id", "x").mapInArrow(norms, "id long, norm double")


def with_local_scale(ds: DataFrame, neighbor: int = 7, sample: int = 1000, seed: int = 42) -> DataFrame:
    """ds with each dense vector's local scale as its last entry, for LocalRbf: the distance to its neighbor-th nearest row of a sample."""
    ship(ds.sparkSession)
    held = ds.sparkSession.sparkContext.broadcast(collect_landmarks(sample_landmarks(ds.select("id", "x"), sample, seed=seed), seed).rows)
    keep = [c for c in ds.columns if c != "x"]

    def scaled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from landmark_kkm.operators.vectors import lists_of

        for batch in batches:
            rows = from_arrow(batch.column("x")).rows
            if len(rows):
                x = np.column_stack([rows, local_scales(Dense(rows), held.value, neighbor)])
                yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), lists_of(x, pa.float64())], names=[*keep, "x"])

    from pyspark.sql import types as T

    return ds.mapInArrow(scaled, T.StructType([*(ds.schema[c] for c in keep), T.StructField("x", T.ArrayType(T.DoubleType(), False))]))

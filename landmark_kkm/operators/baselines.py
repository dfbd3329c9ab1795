"""Baselines: sampled-span kernel k-means, random Fourier features (plain and by singular vectors), two-stage propagation, and plain k-means."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from hashlib import md5

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from landmark_kkm.functions.kernels import Kernel, Laplacian, Rbf
from landmark_kkm.functions.payloads import Sparse, from_arrow
from landmark_kkm.operators import exact
from landmark_kkm.operators.cluster import ClusterModel, cluster
from landmark_kkm.operators.coefficients import KernelColumns, leading
from landmark_kkm.operators.embed import CELLS, embed
from landmark_kkm.operators.landmarks import Landmarks, collect_landmarks, sample_landmarks
from landmark_kkm.operators.vectors import PARTIAL_DDL, lists_of, matrix_of, merged, summed_by_key
from landmark_kkm.session import hold, ship, splits


def _landmarks(ds: DataFrame, l: int, seed: int, landmarks: Landmarks | None) -> Landmarks:
    return landmarks or collect_landmarks(sample_landmarks(ds, l, seed=seed), seed)


def span_kkm(ds: DataFrame, kernel: Kernel, k: int, l: int, max_iter: int = 20, seed: int = 42, landmarks: Landmarks | None = None, rtol: float = 1e-10, **how) -> tuple[DataFrame, ClusterModel]:
    """Kernel k-means whose centroids are combinations of l sampled rows: their kernel values are stored for every row, and each iteration solves the
    centroids' weights through the pseudo-inverse of the landmark kernel. Returns (ds with y, model); y is persisted, for the caller to give back.
    Given the same landmarks and start it assigns as a full-rank Nystrom embedding does."""
    landmarks = _landmarks(ds, l, seed, landmarks)
    gram = kernel.matrix(landmarks.rows, landmarks.rows)
    values, vectors = leading(gram, rtol)
    inverse = vectors / values @ vectors.T
    y = embed(ds, KernelColumns().fit(landmarks, kernel), kernel, "fused", kind="double").persist(StorageLevel.MEMORY_AND_DISK)
    return y, cluster(y, k, "span", max_iter=max_iter, seed=seed, extra=inverse, **how)


def _hashed_uniforms(count: int, seed: int, which: str) -> np.ndarray:
    """Uniforms in (0, 1] from md5, the same in any engine."""
    return np.array([(int(md5(f"{seed}:{which}:{i}".encode()).hexdigest()[:13], 16) + 1) / 2**52 for i in range(count)])


@dataclass
class FourierFeatures:
    """D random frequencies, 2 D features (cosines, then sines) whose inner products approach a shift-invariant kernel: RBF takes normal draws, the Laplacian Cauchy draws.

    draws is "seeded" (a generator) or "md5" (hashes, which SQL can draw too); the number of frequencies does not change the draws."""

    D: int = 500
    kernel: Kernel | None = None
    seed: int = 42
    draws: str = "seeded"

    def frequencies(self, d: int) -> np.ndarray:
        if not isinstance(self.kernel, (Rbf, Laplacian)):
            raise ValueError("random Fourier features need a shift-invariant kernel (RBF or Laplacian)")
        n = self.D * d
        if self.draws not in ("seeded", "md5"):
            raise ValueError("draws is seeded or md5")
        if self.draws == "md5":
            u, v = _hashed_uniforms(n, self.seed, "u"), _hashed_uniforms(n, self.seed, "v")
        else:
            u, v = np.random.default_rng(self.seed).random((2, n)) + 2.0**-60
        if isinstance(self.kernel, Rbf):
            draws = np.sqrt(-2 * np.log(u)) * np.cos(2 * np.pi * v)
        else:
            draws = np.tan(np.pi * (u - 0.5))
        return draws.reshape(self.D, d) / self.kernel.sigma

    def transform(self, ds: DataFrame, d: int | None = None, kind: str = "float") -> DataFrame:
        """ds without x, with y of 2 D values."""
        ship(ds.sparkSession)
        if d is None:
            first = ds.select("x").limit(1).toArrow()
            rows = from_arrow(first.column("x"))
            d = rows.size if isinstance(rows, Sparse) else rows.rows.shape[1]
        held = hold(ds.sparkSession, self.frequencies(d))
        keep = [c for c in ds.columns if c != "x"]
        scale = self.D**-0.5

        def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                rows = from_arrow(batch.column("x"))
                angle = np.vstack([_times(rows.take(np.arange(at, min(at + 1024, len(rows)))), held.value) for at in range(0, len(rows), 1024)] or [np.zeros((0, self_d))])
                y = np.hstack([np.cos(angle), np.sin(angle)]) * scale
                yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), lists_of(y, pa.float32() if kind == "float" else pa.float64())], names=[*keep, "y"])

        self_d = self.D
        schema = T.StructType([ds.schema[c] for c in keep] + [T.StructField("y", T.ArrayType(T.FloatType() if kind == "float" else T.DoubleType(), False))])
        return ds.mapInArrow(features, schema)


def _times(rows, frequencies: np.ndarray) -> np.ndarray:
    if isinstance(rows, Sparse):
        out = np.zeros((len(rows), len(frequencies)))
        for i in range(len(rows)):
            part = slice(rows.start[i], rows.start[i + 1])
            out[i] = frequencies[:, rows.idx[part]] @ rows.val[part]
        return out
    return rows.rows @ frequencies.T


def gram_of_features(y: DataFrame) -> np.ndarray:
    """The inner products of all feature columns over all rows; partitions send one matrix each, merged by rows of the matrix."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for batch in batches:
            if batch.num_rows:
                part = matrix_of(batch.column("y"))
                total = part.T @ part if total is None else total + part.T @ part
        if total is not None:
            n = len(total)
            yield from summed_by_key(iter([pa.RecordBatch.from_arrays([lists_of(total, pa.float64())], names=["y"])]), lambda b: (np.arange(n), matrix_of(b.column("y")), np.ones(n), np.zeros(n), np.zeros(n, np.int64)))

    found = merged(y.select("y").mapInArrow(rows, PARTIAL_DDL), splits(y))
    return np.array([r["z"] for r in found])


@dataclass
class FourierSVD:
    """Left singular vectors of the Fourier feature matrix: the rank leading ones (as many as clusters, unless given)."""

    features: FourierFeatures
    rank: int | None = None
    rtol: float = 1e-12

    def transform(self, ds: DataFrame, k: int, kind: str = "float") -> DataFrame:
        y = self.features.transform(ds, kind="double")
        values, vectors = leading(gram_of_features(y), self.rtol, self.rank or k)
        held = hold(ds.sparkSession, vectors / np.sqrt(values))
        keep = [c for c in y.columns if c != "y"]

        def project(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                if batch.num_rows:
                    yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), lists_of(matrix_of(batch.column("y")) @ held.value, pa.float32() if kind == "float" else pa.float64())], names=[*keep, "y"])

        return y.mapInArrow(project, T.StructType([y.schema[c] for c in keep] + [T.StructField("y", T.ArrayType(T.FloatType() if kind == "float" else T.DoubleType(), False))]))


@dataclass
class Propagator:
    """Labels for rows outside a clustered sample: by its clusters' distances ("centroid"), or by the most similar sample row ("nearest")."""

    landmarks: Landmarks
    labels: np.ndarray
    kernel: Kernel
    k: int
    how: str = "centroid"

    def transform(self, ds: DataFrame) -> DataFrame:
        """ds without x, with cluster and dist (the squared distance less the row's own term, or the similarity with its sign turned)."""
        if self.how not in ("centroid", "nearest"):
            raise ValueError("how is centroid or nearest")
        ship(ds.sparkSession)
        gram = self.kernel.matrix(self.landmarks.rows, self.landmarks.rows)
        member = np.zeros((len(self.labels), self.k))
        member[np.arange(len(self.labels)), self.labels] = 1
        size = member.sum(0)
        share = member / np.where(size > 0, size, 1)
        within = np.where(size > 0, ((gram @ share) * share).sum(0), np.inf)
        held = hold(ds.sparkSession, (self.landmarks.rows, self.kernel, share, within, self.labels, self.how))
        keep = [c for c in ds.columns if c != "x"]

        def label(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            rows, kernel, share, within, labels, how = held.value
            step = max(1, CELLS // max(1, len(rows)))
            for batch in (whole.slice(at, step) for whole in batches for at in range(0, whole.num_rows, step)):
                near = kernel.matrix(from_arrow(batch.column("x")), rows)
                if how == "centroid":
                    d = within - 2 * near @ share
                    best = d.argmin(1)
                    dist = d[np.arange(len(best)), best]
                else:
                    at = near.argmax(1)
                    best, dist = labels[at], -near[np.arange(len(at)), at]
                yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), pa.array(best.astype(np.int32)), pa.array(dist)], names=[*keep, "cluster", "dist"])

        return ds.mapInArrow(label, T.StructType([ds.schema[c] for c in keep] + [T.StructField("cluster", T.IntegerType()), T.StructField("dist", T.DoubleType())]))


def sample_propagate(ds: DataFrame, kernel: Kernel, k: int, l: int, how: str = "centroid", max_iter: int = 20, seed: int = 42, init="kmeans++", landmarks: Landmarks | None = None) -> Propagator:
    """Exact kernel k-means on l sampled rows; the others take labels in one map-only pass (transform)."""
    landmarks = _landmarks(ds, l, seed, landmarks)
    if len(landmarks) < k:
        raise ValueError(f"{len(landmarks)} sampled rows cannot make {k} clusters")
    gram = kernel.matrix(landmarks.rows, landmarks.rows)
    labels, _ = exact.solve(gram, np.diag(gram), k, init, max_iter, seed)
    return Propagator(landmarks, labels, kernel, k, how)


def mllib_kmeans(ds: DataFrame, k: int, seed: int = 42, max_iter: int = 20, bisecting: bool = False) -> DataFrame:
    """(id, cluster) by the library's k-means (or bisecting k-means) on raw dense features."""
    from pyspark.ml.clustering import BisectingKMeans, KMeans
    from pyspark.ml.functions import array_to_vector

    rows = ds.select("id", array_to_vector(F.col("x").cast("array<double>")).alias("features"))
    kind = (BisectingKMeans if bisecting else KMeans)(k=k, seed=seed, maxIter=max_iter, featuresCol="features", predictionCol="cluster")
    return kind.fit(rows).transform(rows).select("id", "cluster")


def power_iteration(edges: DataFrame, k: int, max_iter: int = 20) -> DataFrame:
    """(id, cluster) of a graph's nodes by the library's power iteration clustering: the stand-in for distributed spectral clustering."""
    from pyspark.ml.clustering import PowerIterationClustering

    model = PowerIterationClustering(k=k, maxIter=max_iter, initMode="degree", srcCol="src", dstCol="dst", weightCol="weight")
    return model.assignClusters(edges.select(F.col("src").cast("long"), F.col("dst").cast("long"), F.col("weight").cast("double")))

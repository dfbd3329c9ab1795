"""Embedding families: what makes an embedding out of a row's kernel values against landmarks."""

from __future__ import annotations

from dataclasses import dataclass
from math import pi, sqrt

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from landmark_kkm.functions.kernels import Kernel
from landmark_kkm.functions.payloads import Payload
from landmark_kkm.operators.landmarks import Landmarks


@dataclass
class CoefficientBlock:
    """R (m_b by l_b) and the landmarks whose kernel values it takes."""

    block: int
    landmarks: Landmarks
    R: np.ndarray
    dropped: int = 0  # eigenvalues that were not kept

    @property
    def nbytes(self) -> int:
        return self.R.nbytes + self.landmarks.rows.nbytes()

    def apply(self, rows: Payload, kernel: Kernel) -> np.ndarray:
        return kernel.matrix(rows, self.landmarks.rows) @ self.R.T


def signed(vectors: np.ndarray) -> np.ndarray:
    """Columns with their largest entry positive (the first of equals), as eigenvectors come with either sign."""
    at = np.argmax(np.abs(vectors) > np.abs(vectors).max(0) * (1 - 1e-9), axis=0)
    return vectors * np.where(vectors[at, np.arange(vectors.shape[1])] < 0, -1.0, 1.0)


def leading(matrix: np.ndarray, rtol: float, m: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Positive eigenvalues over rtol times the largest, and their vectors, largest first, m at most."""
    values, vectors = np.linalg.eigh((matrix + matrix.T) / 2)
    values, vectors = values[::-1], vectors[:, ::-1]
    keep = (values > 0) & (values > rtol * max(values.max(), 0.0))
    return values[keep][:m], signed(vectors[:, keep][:, :m])


def centred(matrix: np.ndarray) -> np.ndarray:
    rows = matrix.mean(1, keepdims=True)
    return matrix - rows - matrix.mean(0, keepdims=True) + matrix.mean()


class EmbeddingFamily:
    """fit(landmarks, kernel) gives coefficient blocks; discrepancy names the distance that assignments use; beta() scales it to the kernel distance."""

    discrepancy = "l2"

    def fit(self, landmarks: Landmarks, kernel: Kernel) -> list[CoefficientBlock]:
        raise NotImplementedError

    def beta(self, blocks: list[CoefficientBlock]) -> float | None:
        return None


@dataclass
class Nystrom(EmbeddingFamily):
    """Inverse roots of the leading eigenvalues of the landmark kernel times its eigenvectors. m is capped by the rank, so that m_effective = len(R)."""

    m: int = 500
    rtol: float = 1e-10
    discrepancy = "l2"

    def block(self, landmarks: Landmarks, kernel: Kernel, block: int = 0) -> CoefficientBlock:
        values, vectors = leading(kernel.matrix(landmarks.rows, landmarks.rows), self.rtol, self.m)
        if not len(values):
            raise ValueError("the landmark kernel has no positive eigenvalue")
        return CoefficientBlock(block, landmarks, (vectors / np.sqrt(values)).T, len(landmarks) - len(values))

    def fit(self, landmarks, kernel):
        return [self.block(landmarks, kernel)]

    def beta(self, blocks):
        return 1.0


@dataclass
class NystromEnsemble(EmbeddingFamily):
    """q Nystrom blocks on disjoint landmarks, each portion scaled by the root of its weight, so that inner products average the q kernels."""

    m: int = 500
    q: int = 4
    weights: tuple[float, ...] | None = None
    rtol: float = 1e-10
    discrepancy = "l2"

    def fit(self, landmarks, kernel):
        weights = self.weights or (1 / self.q,) * self.q
        if len(weights) != self.q or min(weights) < 0 or abs(sum(weights) - 1) > 1e-9:
            raise ValueError("weights are q numbers of 0 or more that add to 1")
        out = []
        for b, (part, weight) in enumerate(zip(landmarks.blocks(self.q), weights)):
            one = Nystrom(max(1, self.m // self.q), self.rtol).block(part, kernel, b)
            one.R = one.R * sqrt(weight)
            out.append(one)
        return out

    def beta(self, blocks):
        return 1.0


@dataclass
class StableProjection(EmbeddingFamily):
    """m random directions, each the sum of t landmarks whitened by the landmarks' own covariance in the kernel space; the l1 distance of two
    embeddings is then near a constant times the kernel distance.

    root "symmetric" whitens sums over instances; "eigen" takes the inverse root with one row for each eigen-direction, as the method is often
    written, and is less accurate. t is a count or a share of the landmarks. scale "distance" multiplies so that the l1 distance is itself the estimate."""

    m: int = 500
    t: int | float = 0.4
    root: str = "symmetric"
    scale: str = "none"
    seed: int = 42
    rtol: float = 1e-10
    discrepancy = "l1"

    def count(self, l: int) -> int:
        t = round(self.t * l) if isinstance(self.t, float) else self.t
        if not 1 <= t < l:
            raise ValueError(f"t must be from 1 to {l - 1} of {l} landmarks, not {t}")
        return t

    def inverse_root(self, matrix: np.ndarray) -> tuple[np.ndarray, int]:
        values, vectors = leading(centred(matrix), self.rtol)
        if not len(values):
            raise ValueError("the centred landmark kernel is zero")
        if self.root == "symmetric":
            return vectors / np.sqrt(values) @ vectors.T, len(matrix) - len(values)
        if self.root != "eigen":
            raise ValueError("root is symmetric or eigen")
        whole = np.zeros_like(matrix)
        whole[: len(values)] = (vectors / np.sqrt(values)).T
        return whole, len(matrix) - len(values)

    def fit(self, landmarks, kernel):
        l = len(landmarks)
        t = self.count(l)
        root, dropped = self.inverse_root(kernel.matrix(landmarks.rows, landmarks.rows))
        rng = np.random.default_rng(self.seed)
        rows = np.array([root[rng.choice(l, t, replace=False)].sum(0) for _ in range(self.m)])
        block = CoefficientBlock(0, landmarks, rows, dropped)
        if self.scale == "distance":
            block.R = rows * self.beta([block])
        elif self.scale != "none":
            raise ValueError("scale is none or distance")
        return [block]

    def beta(self, blocks):
        l = len(blocks[0].landmarks)
        t = self.count(l)
        return 1 / (self.m * sqrt(2 / pi) * sqrt(t * (l - t) / (l * (l - 1))))


@dataclass
class KernelColumns(EmbeddingFamily):
    """The kernel values themselves (R is the identity): what the sampled-span baseline works on."""

    discrepancy = "span"

    def fit(self, landmarks, kernel):
        return [CoefficientBlock(0, landmarks, np.eye(len(landmarks)))]


def fit_on_executors(spark: SparkSession, family: Nystrom | StableProjection, landmarks: Landmarks, kernel: Kernel, q: int = 1) -> list[CoefficientBlock]:
    """Nystrom blocks computed by one task each, side by side, rather than on the driver; a stable projection has one block (q is 1)."""
    from landmark_kkm.session import ship

    stable = isinstance(family, StableProjection)
    if stable and q != 1:
        raise ValueError("a stable projection has one block")
    ship(spark)
    parts = landmarks.blocks(q)
    held = spark.sparkContext.broadcast((parts, kernel, family))

    def one(key, _: pd.DataFrame) -> pd.DataFrame:
        blocks, kind, how = held.value
        found = how.fit(blocks[0], kind)[0] if stable else how.block(blocks[key[0]], kind, key[0])
        return pd.DataFrame({"block": key[0], "row": range(len(found.R)), "coef": list(found.R)})

    rows = spark.range(q).selectExpr("cast(id as int) block").groupBy("block").applyInPandas(one, "block int, row int, coef array<double>").toPandas()
    out = []
    for b in range(q):
        R = np.array(rows[rows["block"] == b].sort_values("row")["coef"].tolist()) * (1 / sqrt(q))
        dropped = family.inverse_root(kernel.matrix(landmarks.rows, landmarks.rows))[1] if stable else len(parts[b]) - len(R)
        out.append(CoefficientBlock(b, parts[b], R, dropped))
    return out


def to_frame(spark: SparkSession, blocks: list[CoefficientBlock]) -> DataFrame:
    """(block, row, coef) of all blocks."""
    rows = [(b.block, i, [float(v) for v in r]) for b in blocks for i, r in enumerate(b.R)]
    return spark.createDataFrame(rows, "block int, row int, coef array<double>")


def block_bytes(blocks: list[CoefficientBlock]) -> list[int]:
    return [b.nbytes for b in blocks]


def reconstruct(y: np.ndarray) -> np.ndarray:
    """The low-rank kernel matrix of embedded rows."""
    return y @ y.T

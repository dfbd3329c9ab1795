"""The whole method as an estimator: sample, coefficients, embedding, clustering, labels."""

from __future__ import annotations

import json
import pickle
from base64 import b64decode, b64encode
from dataclasses import dataclass, field
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.ml import Estimator, Model
from pyspark.ml.param import Param, Params, TypeConverters
from pyspark.sql import DataFrame, SparkSession

from landmark_kkm.functions.kernels import Kernel, Rbf, self_tuned_sigma
from landmark_kkm.operators.cluster import ClusterModel, cluster
from landmark_kkm.operators.coefficients import CoefficientBlock, EmbeddingFamily, Nystrom, NystromEnsemble, StableProjection
from landmark_kkm.operators.embed import embed, embedded
from landmark_kkm.operators.landmarks import collect_landmarks, sample_landmarks
from landmark_kkm.operators.ledger import CostLedger, centroid_bytes, embed_bytes, iteration_bytes
from landmark_kkm.session import forced, splits


def _read_embedded(blocks: list[CoefficientBlock], kernel: Kernel, batch: pa.RecordBatch) -> np.ndarray:
    return embedded(batch.column("x"), blocks, kernel)


def family_of(method: str, m: int, t=0.4, q: int = 1, seed: int = 42, **how) -> EmbeddingFamily:
    if method == "nystrom":
        return Nystrom(m) if q == 1 else NystromEnsemble(m, q)
    if method == "stable":
        return StableProjection(m, t, seed=seed, **how)
    raise ValueError("method is nystrom or stable")


class _Settings(Params):
    method = Param(Params._dummy(), "method", "nystrom or stable", TypeConverters.toString)
    l = Param(Params._dummy(), "l", "landmarks", TypeConverters.toInt)
    m = Param(Params._dummy(), "m", "dimensions of the embedding", TypeConverters.toInt)
    t = Param(Params._dummy(), "t", "summed landmarks of a random direction, a share or a count", TypeConverters.toFloat)
    q = Param(Params._dummy(), "q", "blocks of landmarks", TypeConverters.toInt)
    k = Param(Params._dummy(), "k", "clusters", TypeConverters.toInt)
    maxIter = Param(Params._dummy(), "maxIter", "iterations at most", TypeConverters.toInt)
    tol = Param(Params._dummy(), "tol", "share of changed rows at which to stop; under 0: never", TypeConverters.toFloat)
    seed = Param(Params._dummy(), "seed", "seed", TypeConverters.toInt)
    init = Param(Params._dummy(), "init", "random, kmeans++ or partition", TypeConverters.toString)
    storeEmbedding = Param(Params._dummy(), "storeEmbedding", "keep y between iterations, or evaluate it anew", TypeConverters.toBoolean)


@dataclass
class _State:
    blocks: list[CoefficientBlock]
    kernel: Kernel
    model: ClusterModel
    ledger: CostLedger = field(default_factory=CostLedger)


class ScalableKernelKMeans(Estimator, _Settings):
    """fit(ds) on (id, x). Without a kernel, an RBF kernel with a self-tuned width (over the landmarks) is used."""

    def __init__(self, k: int = 8, kernel: Kernel | None = None, method: str = "nystrom", l: int = 300, m: int = 500, t: float = 0.4, q: int = 1, maxIter: int = 20, tol: float = -1.0, seed: int = 42, init: str = "kmeans++", storeEmbedding: bool = True):
        super().__init__()
        self.kernel = kernel
        self._set(k=k, method=method, l=l, m=m, t=t, q=q, maxIter=maxIter, tol=tol, seed=seed, init=init, storeEmbedding=storeEmbedding)

    def _fit(self, ds: DataFrame) -> KernelKMeansModel:
        p = {x.name: self.getOrDefault(x) for x in self.params if self.isDefined(x)}
        ledger = CostLedger(f"{p['method']}-l{p['l']}-m{p['m']}-k{p['k']}")
        with ledger.timed("sample"):
            landmarks = collect_landmarks(sample_landmarks(ds.select("id", "x"), p["l"], seed=p["seed"]), p["seed"])
        kernel = self.kernel or Rbf(self_tuned_sigma(landmarks.rows))
        with ledger.timed("coefficients") as row:
            t = int(p["t"]) if p["t"] >= 1 else float(p["t"])
            family = family_of(p["method"], p["m"], t, p["q"], p["seed"])
            blocks = family.fit(landmarks, kernel)
            row["model_bytes"] = sum(b.nbytes for b in blocks)
        m = sum(len(b.R) for b in blocks)
        how = {"discrepancy": family.discrepancy, "init": p["init"], "max_iter": p["maxIter"], "tol": p["tol"] if p["tol"] >= 0 else None, "seed": p["seed"]}
        if p["storeEmbedding"]:
            with ledger.timed("embed", broadcast_bytes=embed_bytes(blocks)):
                y = forced(embed(ds.select("id", "x"), blocks, kernel, kind="packed"))
            rows, reader = y, None
        else:
            rows, reader = ds.select("id", "x"), partial(_read_embedded, blocks, kernel)
        parts = splits(rows)
        with ledger.timed("cluster", broadcast_bytes=centroid_bytes(p["k"], m) * p["maxIter"], shuffle_bytes=iteration_bytes(parts, p["k"], m) * p["maxIter"]):
            model = cluster(rows, p["k"], reader=reader, **how)
        model.reader = None
        if p["storeEmbedding"]:
            rows.unpersist()
        return KernelKMeansModel(_State(blocks, kernel, model, ledger))


class KernelKMeansModel(Model):
    """transform(ds) adds cluster and dist to (id, x, ...), x left out; embedding and labels are two narrow steps of one stage."""

    def __init__(self, state: _State | None = None):
        super().__init__()
        self.state = state

    @property
    def ledger(self) -> CostLedger:
        return self.state.ledger

    @property
    def centroids(self) -> np.ndarray:
        return self.state.model.centroids

    def _transform(self, ds: DataFrame) -> DataFrame:
        return self.state.model.transform(embed(ds, self.state.blocks, self.state.kernel, "fused"))

    def embedding(self, ds: DataFrame) -> DataFrame:
        return embed(ds, self.state.blocks, self.state.kernel)

    def save(self, spark: SparkSession, path: str) -> None:
        """Centroids as Parquet, and landmarks, coefficients and kernel beside them (load only what you trust: these are pickled)."""
        self.state.model.save(spark, f"{path}/clusters")
        held = b64encode(pickle.dumps((self.state.blocks, self.state.kernel))).decode()
        about = json.dumps({"blocks": len(self.state.blocks), "m": sum(len(b.R) for b in self.state.blocks)})
        spark.createDataFrame([(about, held)], "about string, held string").write.mode("overwrite").parquet(f"{path}/embedding")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> KernelKMeansModel:
        blocks, kernel = pickle.loads(b64decode(spark.read.parquet(f"{path}/embedding").first()["held"]))
        return cls(_State(blocks, kernel, ClusterModel.load(spark, f"{path}/clusters")))

"""Lloyd iterations on vectors: centroids are broadcast, and at most one sum and one count for each cluster leave a partition."""

from __future__ import annotations

import json
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from landmark_kkm.operators.landmarks import digest, sample_landmarks
from landmark_kkm.operators.vectors import PARTIAL_DDL, levels, matrix_of, merged, summed_by_key
from landmark_kkm.session import hold, ship, splits

#: Rows that k-means++ looks at, on the driver.
SEEDING_ROWS = 5000
#: Numbers of one step of l1 distances, which stay in a core's cache.
CELLS = 1 << 17


def costs(y: np.ndarray, centroids: np.ndarray, discrepancy: str, extra: np.ndarray | None = None) -> np.ndarray:
    """A row's cost for each cluster: squared l2, l1, or (span) the squared kernel distance less the row's own term, extra being the inverse landmark kernel."""
    if discrepancy == "l2":
        return np.maximum(np.einsum("ij,ij->i", y, y)[:, None] - 2 * (y @ centroids.T.astype(y.dtype)) + (centroids * centroids).sum(1), 0)
    if discrepancy == "l1":
        n, m = y.shape
        out, step = np.empty((n, len(centroids)), y.dtype), max(1, CELLS // max(1, m))
        centroids, ones, held = centroids.astype(y.dtype), np.ones(m, y.dtype), np.empty((min(step, max(n, 1)), m), y.dtype)
        for at in range(0, n, step):
            part = y[at : at + step]
            gap = held[: len(part)]
            for c, centroid in enumerate(centroids):
                np.subtract(part, centroid, out=gap)
                np.abs(gap, out=gap)
                out[at : at + step, c] = gap @ ones
        return out
    if discrepancy == "span":
        alpha = centroids @ extra
        return (alpha * centroids).sum(1) - 2 * y @ alpha.T
    raise ValueError("discrepancy is l2, l1 or span")


@dataclass
class ClusterModel:
    centroids: np.ndarray
    sizes: np.ndarray
    discrepancy: str = "l2"
    history: list[dict] = field(default_factory=list)
    extra: np.ndarray | None = None
    reader: Callable | None = None  # batch to vectors, if not the column y

    def transform(self, ds: DataFrame) -> DataFrame:
        """ds without its vector, with cluster and dist (the lowest index wins a tie)."""
        ship(ds.sparkSession)
        held = hold(ds.sparkSession, (self.centroids, self.discrepancy, self.extra, self.reader))
        keep = [c for c in ds.columns if c not in ("x", "y")]

        def label(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            centroids, discrepancy, extra, reader = held.value
            for batch in batches:
                if not batch.num_rows:
                    continue
                cost = costs(_vectors(batch, reader), centroids, discrepancy, extra)
                best = cost.argmin(1)
                least = cost[np.arange(len(best)), best]
                dist = np.sqrt(np.maximum(least, 0)) if discrepancy == "l2" else least
                yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), pa.array(best.astype(np.int32)), pa.array(dist.astype(float))], names=[*keep, "cluster", "dist"])

        return ds.mapInArrow(label, T.StructType([ds.schema[c] for c in keep] + [T.StructField("cluster", T.IntegerType()), T.StructField("dist", T.DoubleType())]))

    def to_frame(self, spark: SparkSession) -> DataFrame:
        rows = [(len(self.history), c, [float(v) for v in y], float(g)) for c, (y, g) in enumerate(zip(self.centroids, self.sizes))]
        return spark.createDataFrame(rows, "iter int, cluster int, centroid array<double>, n double")

    def save(self, spark: SparkSession, path: str) -> None:
        about = json.dumps({"discrepancy": self.discrepancy, "history": self.history, "extra": self.extra.tolist() if self.extra is not None else None})
        self.to_frame(spark).withColumn("about", F.lit(about)).write.mode("overwrite").parquet(path)

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> ClusterModel:
        rows = spark.read.parquet(path).orderBy("cluster").collect()
        about = json.loads(rows[0]["about"])
        return cls(np.array([r["centroid"] for r in rows]), np.array([r["n"] for r in rows]), about["discrepancy"], about["history"], np.array(about["extra"]) if about["extra"] else None)


def _vectors(batch: pa.RecordBatch, reader: Callable | None) -> np.ndarray:
    return matrix_of(batch.column("y")) if reader is None else reader(batch)


def plus_plus(rows: np.ndarray, k: int, discrepancy: str, rng: np.random.Generator, extra=None) -> np.ndarray:
    """k rows, each drawn with a chance that grows with its cost to those drawn before."""
    chosen = [int(rng.integers(len(rows)))]
    cost = costs(rows, rows[chosen], discrepancy, extra)[:, 0]
    while len(chosen) < k:
        weight = np.maximum(cost - cost.min() if discrepancy == "span" else cost, 0)
        if discrepancy == "l1":
            weight = weight * weight
        weight[chosen] = 0
        chosen.append(int(rng.choice(len(rows), p=weight / weight.sum())) if weight.sum() > 0 else next(i for i in range(len(rows)) if i not in chosen))
        cost = np.minimum(cost, costs(rows, rows[chosen[-1:]], discrepancy, extra)[:, 0])
    return rows[chosen]


def first_centroids(ds: DataFrame, k: int, init, discrepancy: str, seed: int, reader=None, extra=None) -> np.ndarray:
    """"random": the k rows with the least digests; "kmeans++": on SEEDING_ROWS such rows; "partition": means of a random partition; or an array."""
    if isinstance(init, np.ndarray):
        if len(init) != k:
            raise ValueError("as many centroids as clusters are needed")
        return init.astype(float)
    if init == "partition":
        keys = F.pmod(F.conv(F.substring(digest(seed=seed), 1, 8), 16, 10).cast("long"), F.lit(k)).cast("int")
        ds = ds.withColumn("_key", keys)

        def of(batch):
            y = _vectors(batch, reader)
            n = len(y)
            return batch.column("_key").to_numpy(), y, np.ones(n), np.zeros(n), np.zeros(n, np.int64)

        rows = merged(ds.mapInArrow(lambda it: summed_by_key(it, of), PARTIAL_DDL), splits(ds))
        if len(rows) < k:
            raise ValueError("fewer rows than clusters")
        return np.array([np.array(r["z"]) / r["g"] for r in rows])
    if init not in ("random", "kmeans++"):
        raise ValueError("init is random, kmeans++, partition or an array")
    top = sample_landmarks(ds, k if init == "random" else max(k, SEEDING_ROWS), seed=seed).toArrow()
    if top.num_rows < k:
        raise ValueError(f"{k} clusters need {k} rows, there are {top.num_rows}")
    rows = np.vstack([_vectors(b, reader) for b in top.combine_chunks().to_batches()])
    return rows[:k] if init == "random" else plus_plus(rows, k, discrepancy, np.random.default_rng(seed), extra)


def cluster(
    ds: DataFrame, k: int, discrepancy: str = "l2", init="kmeans++", max_iter: int = 20, tol: float | None = None, seed: int = 42, empty: str = "keep",
    weight_col: str | None = None, combine: bool = True, extra: np.ndarray | None = None, reader: Callable | None = None,
) -> ClusterModel:
    """A model of k clusters of ds (id, y). Each iteration is one job; what it moves is k sums and counts for each partition, and no lineage grows.

    Stops after max_iter iterations, or (tol) once the share of rows that changed cluster is at most tol; changes are counted only with a tol, as that
    takes each row's distances to the centroids before. empty "keep" leaves an empty cluster's
    centroid, "reseed_farthest" puts it on the row that is farthest from its own. combine=False ships every row to its cluster (for comparison only).
    reader takes the vectors from a batch, for embeddings that are not stored. The mean update lowers the l2 cost in each iteration; it need not lower the l1 cost."""
    if k < 1:
        raise ValueError("k must be at least 1")
    if empty not in ("keep", "reseed_farthest"):
        raise ValueError("empty is keep or reseed_farthest")
    spark = ds.sparkSession
    ship(spark)
    centroids = first_centroids(ds, k, init, discrepancy, seed, reader, extra)
    sizes, before, history = np.zeros(k), None, []
    partitions = levels(splits(ds), centroids.size * 8 * (2 if empty == "reseed_farthest" else 1))
    if reader is None:  # ids and classes stay where they are
        ds = ds.select("y", *([weight_col] if weight_col else []))
    for step in range(max_iter):
        held = spark.sparkContext.broadcast((centroids, before if tol is not None else None, extra, reader))

        def of(batch, held=held):
            now, old, more, read = held.value
            y = _vectors(batch, read)
            cost = costs(y, now, discrepancy, more)
            best = cost.argmin(1)
            changed = best != costs(y, old, discrepancy, more).argmin(1) if old is not None else np.ones(len(best), bool)
            weight = batch.column(weight_col).to_numpy() if weight_col else np.ones(len(best))
            return best.astype(np.int64), y, weight, cost[np.arange(len(best)), best], changed

        if combine:
            far = empty == "reseed_farthest"
            rows = merged(ds.mapInArrow(lambda it, of=of, far=far: summed_by_key(it, of, far), PARTIAL_DDL), partitions)
        else:
            rows = _uncombined(ds, of, empty == "reseed_farthest")
        held.destroy()
        new, sizes = centroids.copy(), np.zeros(k)
        for r in rows:
            sizes[r["key"]] = r["g"]
            if r["g"] > 0:
                new[r["key"]] = np.array(r["z"]) / r["g"]
        if empty == "reseed_farthest":
            far = sorted(rows, key=lambda r: -r["far"])
            for c, r in zip(np.flatnonzero(sizes == 0), far):
                new[c] = np.array(r["far_y"])
        changed, n = sum(r["changed"] for r in rows), sizes.sum()
        history.append({"iter": step, "cost": float(sum(r["sse"] for r in rows)), "changed": int(changed) if tol is not None else None, "shift": float(np.abs(new - centroids).max()), "empty": int((sizes == 0).sum())})
        before, centroids = centroids, new
        if tol is not None and step and changed <= tol * max(n, 1):
            break
    return ClusterModel(centroids, sizes, discrepancy, history, extra, reader)


def _uncombined(ds: DataFrame, of, far: bool = False) -> list:
    """The same sums with every row sent to its cluster: n vectors move where k sums for each partition would do."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from landmark_kkm.operators.vectors import Partials

        for batch in batches:
            for i in range(batch.num_rows):
                held = Partials(far)
                held.add(*of(batch.slice(i, 1)))
                yield held.batch()

    return merged(ds.mapInArrow(rows, PARTIAL_DDL), 1)


def lloyd(ds: DataFrame, k: int, **how) -> ClusterModel:
    """Plain k-means on explicit vectors (id, x), by the same loop."""
    return cluster(ds.withColumnRenamed("x", "y"), k, **how)

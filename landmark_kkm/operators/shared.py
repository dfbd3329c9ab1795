"""Graphs of rows that have enough bits in common: links, components, power iteration and the spectral route, with no edge as a row."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from landmark_kkm.functions.kernels import SharedBits
from landmark_kkm.functions.payloads import Objects
from landmark_kkm.operators.exact import BLOCK, PIECE, KKMResult, _distances, _first_labels
from landmark_kkm.operators.landmarks import digest
from landmark_kkm.operators.vectors import lists_of, matrix_of
from landmark_kkm.session import ship


class Graph:
    """The rows of ds (id, x binary), two of them linked if `least` bits or more are in both. The driver and each worker hold the distinct values of x and how often
    each occurs; a pass evaluates all pairs of distinct values in tasks, block by block."""

    def __init__(self, ds: DataFrame, least: int = 2):
        self.spark: SparkSession = ds.sparkSession
        ship(self.spark)
        table = ds.select("id", "x").toArrow().sort_by("id")
        self.ids = table.column("id").to_numpy()
        distinct = table.column("x").combine_chunks().dictionary_encode()
        distinct = distinct.combine_chunks() if isinstance(distinct, pa.ChunkedArray) else distinct
        self.of = distinct.indices.to_numpy()
        rows = Objects(distinct.dictionary.to_pylist())
        self.times = np.bincount(self.of, minlength=len(rows)).astype(float)
        self.kernel = SharedBits(least)
        self.own = self.kernel.diagonal(rows)
        self.held = self.spark.sparkContext.broadcast((rows, self.kernel))

    def _pass(self, values: np.ndarray, fold: Callable, start: float, width: int, columns: np.ndarray | None = None) -> np.ndarray:
        """width numbers for each distinct value: fold(out, weights of its links to a block, values of the block) over all blocks, or those of some distinct values."""
        n, data = len(self.times), self.held
        more = self.spark.sparkContext.broadcast((values, np.arange(n) if columns is None else columns))

        def of(batches):
            rows, kernel = data.value
            values, columns = more.value
            for batch in batches:
                at = batch.column("pos").to_numpy()
                out = np.full((len(at), width), start)
                for i in range(0, len(at), BLOCK):
                    own = rows.take(at[i : i + BLOCK])
                    for j in range(0, len(columns), BLOCK):
                        fold(out[i : i + BLOCK], kernel.matrix(own, rows.take(columns[j : j + BLOCK])), values[j : j + BLOCK])
                yield pa.RecordBatch.from_arrays([pa.array(at), lists_of(out, pa.float64())], names=["pos", "v"])

        tasks = max(1, min(4 * self.spark.sparkContext.defaultParallelism, n // 64))
        found = self.spark.range(0, n, 1, tasks).select(F.col("id").alias("pos")).mapInArrow(of, "pos long, v array<double>").toArrow().sort_by("pos")
        more.destroy()
        return matrix_of(found.column("v"))

    def degrees(self) -> tuple[np.ndarray, np.ndarray]:
        """The number of links of each distinct value's rows, and their weight; a row has no link to itself."""

        def fold(out, w, times):
            out[:, 0] += (w > 0) @ times
            out[:, 1] += w @ times

        found = self._pass(self.times, fold, 0.0, 2) if len(self.times) else np.zeros((0, 2))
        return found[:, 0] - (self.own > 0), found[:, 1] - self.own

    def multiply(self, v: np.ndarray) -> np.ndarray:
        """The adjacency matrix times a vector that has one number for each distinct value."""

        def fold(out, w, x):
            out[:, 0] += w @ x

        return self._pass(self.times * v, fold, 0.0, 1)[:, 0] - self.own * v

    def shares(self, columns: np.ndarray, counts: np.ndarray) -> np.ndarray:
        """Each distinct value's weight of links to counts (len(columns) by k) rows of the distinct values at columns, those of its own value included."""

        def fold(out, w, x):
            out += w @ x

        return self._pass(counts, fold, 0.0, counts.shape[1], columns)

    def links_of(self, one: int) -> np.ndarray:
        """The weight of each distinct value's link to a row of the distinct value `one`."""
        rows = self.held.value[0]
        return np.concatenate([self.kernel.matrix(rows.take(np.arange(at, min(at + PIECE, len(rows)))), rows.take([one]))[:, 0] for at in range(0, len(rows), PIECE)])

    def components(self) -> np.ndarray:
        """The component of each distinct value, by the place of one of its members. Rows of equal values are linked if they have bits enough; else they are rows without a link."""
        n = len(self.times)
        root = np.arange(n)

        def fold(out, w, label):
            out[:, 0] = np.minimum(out[:, 0], np.where(w > 0, label, np.inf).min(1))

        while n:
            near = np.minimum(self._pass(root.astype(float), fold, np.inf, 1)[:, 0], root).astype(int)
            if (near == root).all():
                break
            for a, b in {*zip(root[near != root].tolist(), near[near != root].tolist())}:  # union by the lesser root
                while root[a] != a:
                    a = root[a]
                while root[b] != b:
                    b = root[b]
                root[max(a, b)] = min(a, b)
            while (root[root] != root).any():
                root = root[root]
            if len(np.unique(root[self.own > 0])) < 2:  # no two components are left to join
                break
        return root


def links(ds: DataFrame, least: int = 2) -> DataFrame:
    """(id, component, links, weight): each row's component (the least id reachable, itself included), its number of links and the bits shared over them."""
    g = Graph(ds, least)
    count, weight = (x.round().astype(np.int64)[g.of] for x in g.degrees())
    of = g.components()[g.of]
    first = np.full(len(g.times), np.iinfo(np.int64).max)
    np.minimum.at(first, of, g.ids)
    component = np.where(count > 0, first[of], g.ids)
    return g.spark.createDataFrame(pa.table({"id": pa.array(g.ids), "component": pa.array(component), "links": pa.array(count), "weight": pa.array(weight)}))


def power_iteration(ds: DataFrame, k: int, least: int = 2, max_iter: int = 20) -> DataFrame:
    """(id, cluster) of the linked rows by power iteration clustering from the degrees: the stand-in for distributed spectral clustering. Rows of equal values have equal
    entries of the vector throughout, so one number for each distinct value is iterated; the library's k-means splits the rows by it."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    g = Graph(ds, least)
    degree = g.degrees()[1]
    v = degree / max(g.times @ degree, 1)
    delta = np.inf
    for _ in range(max_iter):
        new = np.divide(g.multiply(v), degree, out=np.zeros(len(v)), where=degree > 0)
        new /= max(g.times @ np.abs(new), 1e-300)
        moved = float(g.times @ np.abs(new - v))
        v = new
        if abs(delta - moved) < max(1e-5 / max(len(g.ids), 1), 1e-8):
            break
        delta = moved
    linked = degree[g.of] > 0
    if not linked.any():
        return g.spark.createDataFrame([], "id long, cluster int")
    rows = g.spark.createDataFrame(pa.table({"id": pa.array(g.ids[linked]), "v": v[g.of][linked]})).select("id", array_to_vector(F.array("v")).alias("features"))
    return KMeans(k=k, seed=0, featuresCol="features", predictionCol="cluster").fit(rows).transform(rows).select("id", "cluster")


def spectral_cluster(ds: DataFrame, k: int, least: int = 2, shift: float = 1.0, init="kmeans++", max_iter: int = 20, seed: int = 42, patience: int | None = None) -> KKMResult:
    """Clusters of the linked rows by weighted kernel k-means, with no eigenvectors and no edges. Rows without a link are not in the result.

    The shift adds the same number to the cost of every clustering, but a row moves only if it gains more than its share of it: with 1.0, where the cost never rises, no row of a
    dense graph moves from any start. With 0.0 links alone decide, and the cost may rise between steps; patience then ends the loop after so many steps without a lower cost,
    and the labels of the least cost are the result. Rows of equal values share their sums, so a step evaluates pairs of distinct values, after the first those that changed."""
    g = Graph(ds, least)
    degree = g.degrees()[1]
    ids = ds.select("id", digest(seed=seed).alias("_digest")).toArrow().sort_by([("_digest", "ascending"), ("id", "ascending")]).column("id").to_numpy()
    of = g.of[np.searchsorted(g.ids, ids)]
    linked = degree[of] > 0
    ids, of = ids[linked], of[linked]
    n, values, w = len(ids), len(g.times), degree[of]
    if n < k:
        raise ValueError("fewer rows than clusters")
    diagonal = shift / w

    def column(c: int) -> np.ndarray:
        found = g.links_of(of[c])[of] / (w * w[c])
        found[c] = diagonal[c]
        return found

    labels = _first_labels(ids, column, diagonal, k, init, seed)
    sums, before, history, best = np.zeros((values, k)), np.zeros((values, k)), [], (np.inf, 0, labels)
    for i in range(max_iter):
        now = np.bincount(of * k + labels, minlength=values * k).reshape(values, k).astype(float)
        moved = np.flatnonzero((now != before).any(1))
        if len(moved):
            sums += g.shares(moved, now[moved] - before[moved])  # whole numbers, without rounding
        before = now
        s = sums[of] / w[:, None]
        s[np.arange(n), labels] += shift - g.own[of] / w  # a row's link to itself is none
        d = _distances(s, diagonal, labels, w)
        new = d.argmin(1)
        cost = float(w @ d[np.arange(n), labels])
        history.append({"iter": i, "cost": cost, "changed": int((new != labels).sum())})
        if cost < best[0]:
            best = cost, i, labels
        labels = new
        if not history[-1]["changed"] or patience is not None and i - best[1] >= patience:
            break
    return KKMResult(ids, labels if patience is None else best[2], history)

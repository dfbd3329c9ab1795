"""Landmark sampling by a hash of the id, so that a sample does not depend on how rows are partitioned or retried."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from landmark_kkm.functions.payloads import Payload, from_arrow


def digest(id_col: str = "id", seed: int = 42) -> Column:
    return F.md5(F.concat_ws(":", F.col(id_col).cast("string"), F.lit(str(seed))))


def uniform(id_col: str = "id", seed: int = 42) -> Column:
    """A number in [0, 1) from the first 52 bits of the digest."""
    return F.conv(F.substring(digest(id_col, seed), 1, 13), 16, 10).cast("double") / F.lit(float(1 << 52))


def sample_landmarks(ds: DataFrame, l: int, method: str = "exact", seed: int = 42, n: int | None = None) -> DataFrame:
    """l rows with the least digests ("exact"), or each row with probability l / n ("bernoulli", of random size with mean l).

    "exact" filters on the digest first, so that the top-l sort sees about 2l rows; should too few pass, it sees all."""
    if l < 1:
        raise ValueError("l must be at least 1")
    if method not in ("exact", "bernoulli"):
        raise ValueError("method is exact or bernoulli")
    n = ds.count() if n is None else n
    if method == "bernoulli":
        return ds.filter(uniform(seed=seed) < l / max(n, 1))
    if n > 4 * l:
        near = ds.filter(uniform(seed=seed) < 2 * l / n)
        if near.select("id").count() >= l:
            ds = near
    return ds.withColumn("_digest", digest(seed=seed)).orderBy("_digest", "id").limit(l).drop("_digest")


def split_blocks(landmarks: DataFrame, q: int, seed: int = 42) -> DataFrame:
    """Landmarks with `block` (0 to q - 1, disjoint, sizes at most one apart) and `pos`; a sample is small, so one task numbers it."""
    rank = F.row_number().over(Window.orderBy(digest(seed=seed), "id")) - 1
    return landmarks.withColumn("pos", rank).withColumn("block", F.pmod(F.col("pos"), F.lit(q)))


@dataclass
class Landmarks:
    ids: np.ndarray
    rows: Payload

    def __len__(self) -> int:
        return len(self.ids)

    def blocks(self, q: int) -> list[Landmarks]:
        """Disjoint blocks, dealt in turn; rows are in digest order."""
        if q < 1 or q > len(self):
            raise ValueError(f"{len(self)} landmarks cannot make {q} blocks")
        return [Landmarks(self.ids[b::q], self.rows.take(np.arange(b, len(self), q))) for b in range(q)]


def collect_landmarks(landmarks: DataFrame, seed: int = 42) -> Landmarks:
    """The sample on the driver, in digest order."""
    table = landmarks.withColumn("_digest", digest(seed=seed)).select("_digest", "id", "x").toArrow().sort_by([("_digest", "ascending"), ("id", "ascending")])
    if table.num_rows < 2:
        raise ValueError("fewer than two landmarks were sampled")
    return Landmarks(table.column("id").to_numpy(), from_arrow(table.column("x")))

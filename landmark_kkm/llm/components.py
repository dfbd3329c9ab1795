"""Connected components by alternating stars, on DataFrames alone."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from landmark_kkm.session import materialize


def _with_least(rows: DataFrame) -> DataFrame:
    """Each row (u, v) with m, the least of u and all v beside it. The aggregate combines before it shuffles."""
    least = rows.groupBy("u").agg(F.min("v").alias("least"))
    return rows.join(least, "u").select("u", "v", F.least("u", "least").alias("m"))


def _large(edges: DataFrame) -> DataFrame:
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    return _with_least(both).filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").distinct()


def _small(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    starred = _with_least(down)
    return (
        starred.select(F.col("v").alias("u"), F.col("m").alias("v"))
        .unionByName(starred.select("u", F.col("m").alias("v")))
        .filter("u <> v")
        .distinct()
    )


def components(edges: DataFrame, max_rounds: int = 64) -> DataFrame:
    """(node, component) for every node that an edge (u, v) names; component is the least node that can be reached.

    Each round is two stars, each a combine-first aggregate and a join whose one side has unique keys (so a hub's rows can be split).
    Rounds grow with the logarithm of the longest path. Self links and nulls are ignored; no edges give no rows.
    """
    now = materialize(edges.select(F.col("u").cast("long"), F.col("v").cast("long")).filter("u <> v").distinct(), "edges")
    digest = None
    for _ in range(max_rounds):
        now = materialize(_small(_large(now)), "stars")
        count, total = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if digest == (count, total) or not count:
            break
        digest = (count, total)
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(
        now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    )

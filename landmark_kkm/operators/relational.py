"""Joins, windows and aggregates that the engine's users need around clustering and Spark has no single operator for."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def asof_join(left: DataFrame, right: DataFrame, left_time: str, right_time: str, by: list[str] | None = None, values: list[str] | None = None) -> DataFrame:
    """left with the values of the last right row (of the same `by`) at or before its time; null if there is none.

    One union and one window, so one shuffle by the keys; no pair of rows is formed. Without keys all rows would go to one task, so `by` must be given.
    Of right rows with one time, that with the greatest values counts."""
    if not by:
        raise ValueError("an as-of join needs keys: without them one task would sort all rows")
    values = values or [c for c in right.columns if c not in (*by, right_time)]
    a = left.withColumn("_t", F.col(left_time)).withColumn("_right", F.lit(0)).withColumn("_v", F.lit(None).cast(right.select(F.struct(*values)).schema[0].dataType))
    b = right.select(*by, F.col(right_time).alias("_t"), F.lit(1).alias("_right"), F.struct(*values).alias("_v"))
    both = a.unionByName(b, allowMissingColumns=True)
    # at equal times right rows come first, so that they are seen
    order = Window.partitionBy(*by).orderBy("_t", F.desc("_right"), F.col("_v")).rowsBetween(Window.unboundedPreceding, 0)
    seen = both.withColumn("_last", F.last("_v", ignorenulls=True).over(order)).filter("_right = 0")
    return seen.select(*left.columns, *[F.col("_last")[v].alias(v) for v in values])


def interval_join(left: DataFrame, right: DataFrame, left_time: str, right_time: str, before: int, by: list[str], bucket: int | None = None) -> DataFrame:
    """Pairs with right's time in the `before` seconds up to left's (both ends included), for equal keys.

    Times are cut into buckets of `bucket` seconds, so that the join is on equality: each right row is sent to the buckets that its interval reaches."""
    width = bucket or max(before, 1)
    seconds = lambda c: F.unix_micros(F.col(c).cast("timestamp")) / 1_000_000
    at = lambda s: F.floor(s / width).cast("long")
    a = left.withColumn("_b", at(seconds(left_time)))
    b = right.withColumn("_b", F.explode(F.sequence(at(seconds(right_time)), at(seconds(right_time) + before))))
    renamed = b.select(*[F.col(c).alias(f"_k{i}") for i, c in enumerate(by)], "_b", *[F.col(c).alias(f"{c}_r" if c in left.columns else c) for c in right.columns if c not in by])
    time = f"{right_time}_r" if right_time in left.columns else right_time
    keys = [a[c] == renamed[f"_k{i}"] for i, c in enumerate(by)] + [a["_b"] == renamed["_b"]]
    met = a.join(renamed, keys, "inner").drop(renamed["_b"]).drop("_b", *[f"_k{i}" for i in range(len(by))])
    gap = seconds(left_time) - seconds(time)
    return met.filter((gap >= 0) & (gap <= before))


def vector_sum(df: DataFrame, key: str, column: str) -> DataFrame:
    """(key, sum, n): element-wise sums of dense vectors, within the JVM; a twin of the loop's merge."""
    cells = df.select(key, F.posexplode(F.col(column).cast("array<double>")).alias("p", "v")).groupBy(key, "p").agg(F.sum("v").alias("v"), F.count("*").alias("n"))
    rows = cells.groupBy(key).agg(F.sort_array(F.collect_list(F.struct("p", "v"))).alias("c"), F.max("n").alias("n"))
    return rows.select(key, F.transform("c", lambda c: c["v"]).alias("sum"), "n")


def lloyd_step(ds: DataFrame, centroids: DataFrame, distance) -> DataFrame:
    """(cluster, centroid, n) after one step of k-means as a relational plan: the few centroids are broadcast, ties go to the lower cluster."""
    pairs = ds.select("id", "x").crossJoin(F.broadcast(centroids.select("cluster", "centroid")))
    best = pairs.groupBy("id").agg(F.min(F.struct(distance(F.col("x"), F.col("centroid")).alias("d"), "cluster")).alias("b"), F.first("x").alias("x"))
    sums = vector_sum(best.select(F.col("b.cluster").alias("cluster"), "x"), "cluster", "x")
    return sums.select("cluster", F.transform("sum", lambda v: v / F.col("n")).alias("centroid"), "n")


def exemplars(assigned: DataFrame, top: int = 3) -> DataFrame:
    """The rows nearest to their centroid, `top` for each cluster, by (dist, id)."""
    order = Window.partitionBy("cluster").orderBy("dist", "id")
    return assigned.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= top)


def moving_mix(events: DataFrame, key: str, time: str, kind: str, rows: int = 10) -> DataFrame:
    """events with the number of kinds among each row and the `rows` - 1 before it, by key."""
    frame = Window.partitionBy(key).orderBy(time, *([c for c in ("event_id",) if c in events.columns])).rowsBetween(-(rows - 1), 0)
    return events.withColumn("kinds", F.size(F.collect_set(kind).over(frame)))


def salted_count(df: DataFrame, key: str, salts: int = 16, salt: Column | None = None) -> DataFrame:
    """Counts by key in two levels, for aggregates that cannot combine before the shuffle."""
    s = F.pmod(F.xxhash64(*df.columns), F.lit(salts)) if salt is None else salt
    return df.groupBy(key, s.alias("_s")).agg(F.count("*").alias("n")).groupBy(key).agg(F.sum("n").alias("n"))

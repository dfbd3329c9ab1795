"""Streams: scoring with a fitted model, windows, per-user state, centroid updates, duplicates, and joins with tables."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from landmark_kkm.operators.cluster import ClusterModel, cluster
from landmark_kkm.session import new_path, ship


def read_stream(spark: SparkSession, path: str, name: str, files_per_trigger: int | None = None) -> DataFrame:
    """A stream of the Parquet files of a table (a folder, or a file's own folder with its name as the pattern); zoneless timestamps are cast, as watermarks ask."""
    schema = spark.read.parquet(f"{path}/{name}.parquet").schema
    reader = spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet")
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    df = reader.parquet(f"{path}/{name}.parquet*")
    return df.select(*[F.col(f.name).cast("timestamp").alias(f.name) if f.dataType.simpleString() == "timestamp_ntz" else F.col(f.name) for f in schema.fields])


def run_available(df: DataFrame, mode: str = "append", query_name: str | None = None) -> DataFrame:
    """Process what there is and return the result as a table in the shared folder: all rows (append), the rows of each batch (update), or the last batch (complete)."""
    spark, path, batches = df.sparkSession, new_path(df.sparkSession, "sink"), []
    writer = df.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", new_path(spark, "stream"))
    if mode == "append":
        writer.format("parquet").option("path", path).start().awaitTermination()
        return spark.read.schema(df.schema).parquet(path)

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/{number}")
        batches.append(f"{path}/{number}")

    writer = writer.queryName(query_name) if query_name else writer
    writer.foreachBatch(write).start().awaitTermination()
    if not batches:
        return spark.createDataFrame([], df.schema)
    return spark.read.schema(df.schema).parquet(*(batches[-1:] if mode == "complete" else sorted(set(batches))))


def run_reported(df: DataFrame) -> tuple[DataFrame, int]:
    """What run_available gives in append mode, and the number of rows that came behind the watermark and were dropped.

    The number is that of the stateful operators' own progress, gathered batch by batch, as a query keeps only its last reports. Operators that add up
    rows before they shuffle them (windows, sessions) report partial sums, not rows; duplicates are reported row by row."""
    spark, path, started, dropped = df.sparkSession, new_path(df.sparkSession, "sink"), [], {}

    def note() -> None:
        for progress in started[0].recentProgress if started else ():
            dropped[progress["batchId"]] = max(dropped.get(progress["batchId"], 0), sum(s["numRowsDroppedByWatermark"] for s in progress["stateOperators"]))

    def write(batch: DataFrame, number: int) -> None:
        note()
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    started.append(df.writeStream.trigger(availableNow=True).option("checkpointLocation", new_path(spark, "stream")).foreachBatch(write).start())
    started[0].awaitTermination()
    note()
    found = spark.read.schema(df.schema).parquet(path).drop("batch") if dropped else spark.createDataFrame([], df.schema)
    return found.select(*df.columns), sum(dropped.values())


def replayed(parts: list[DataFrame], files_per_trigger: int = 1) -> DataFrame:
    """A stream of the given tables of one schema, one after the other: rows that arrive in another order than their times."""
    spark, path = parts[0].sparkSession, new_path(parts[0].sparkSession, "replay")
    for part in parts:
        part.write.mode("append").parquet(path)
    return spark.readStream.schema(parts[0].schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def score(stream: DataFrame, model: ClusterModel, embedder: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """Rows (id, x or y, ...) with cluster and dist; stateless, so it scales as a batch does."""
    ship(stream.sparkSession)
    return model.transform(embedder(stream) if embedder else stream)


def windowed_mix(stream: DataFrame, time: str, kind: str, width: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Counts of kinds in tumbling (or, with slide, sliding) windows; rows behind the watermark are dropped (run_reported counts them)."""
    window = F.window(time, width, slide) if slide else F.window(time, width)
    return stream.withWatermark(time, late).groupBy(window.alias("w"), kind).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), kind, "n")


def sessions(stream: DataFrame, time: str, key: str, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """Sessions of each key: runs of rows less than `gap` apart."""
    return stream.withWatermark(time, late).groupBy(F.session_window(time, gap).alias("w"), key).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), key, "n")


def deduplicated(stream: DataFrame, time: str, keys: list[str], late: str = "1 hour") -> DataFrame:
    return stream.withWatermark(time, late).dropDuplicatesWithinWatermark(keys)


def with_table(stream: DataFrame, table: DataFrame, on: list[str]) -> DataFrame:
    """A stream joined with a table that does not change."""
    return stream.join(table, on, "left")


def running_histograms(stream: DataFrame, key: str, kind: str, kinds: list[str], model: ClusterModel | None = None) -> DataFrame:
    """(key, events, x[, cluster]) in each batch that brings rows of the key: counts of each kind so far, and the nearest centroid of their shares.

    The state of a key is one number for each kind."""
    ship(stream.sparkSession)
    held = (model.centroids, model.discrepancy) if model is not None else None
    ddl = f"{key} long, events long, x array<double>, cluster int"

    def update(keys, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        from landmark_kkm.operators.cluster import costs

        counts = np.array(state.get[0], dtype=float) if state.exists else np.zeros(len(kinds))
        for part in parts:
            found = part[kind].value_counts()
            counts += np.array([float(found.get(k, 0)) for k in kinds])
        state.update((counts.tolist(),))
        share = counts / max(counts.sum(), 1)
        best = int(costs(share[None], *held).argmin()) if held else -1
        yield pd.DataFrame({key: [keys[0]], "events": [int(counts.sum())], "x": [counts.tolist()], "cluster": [best]})

    return stream.groupBy(key).applyInPandasWithState(update, ddl, "counts array<double>", "update", GroupStateTimeout.NoTimeout)


class MiniBatchCentroids:
    """Centroids that follow a stream: each batch's sums and counts are added to what is kept of the earlier ones (decay)."""

    def __init__(self, model: ClusterModel, decay: float = 0.9):
        self.model, self.decay = model, decay
        self.weight = np.maximum(model.sizes.astype(float), 0)

    def update(self, batch: DataFrame, _: int = 0) -> None:
        """For foreachBatch: one step of the loop on the batch (id, y)."""
        if batch.isEmpty():
            return
        one = cluster(batch, len(self.model.centroids), self.model.discrepancy, init=self.model.centroids, max_iter=1)
        kept = self.weight * self.decay
        total = kept + one.sizes
        share = np.divide(one.sizes, total, out=np.zeros_like(total), where=total > 0)[:, None]
        self.model.centroids = self.model.centroids * (1 - share) + one.centroids * share
        self.weight = total
        self.model.sizes = total

    def follow(self, stream: DataFrame) -> None:
        stream.writeStream.foreachBatch(self.update).trigger(availableNow=True).option("checkpointLocation", new_path(stream.sparkSession, "follow")).start().awaitTermination()

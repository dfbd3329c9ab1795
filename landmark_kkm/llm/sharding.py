"""Sharding by longest processing time: groups that stay together go, largest first, to the least-loaded shard of a heap.

Groups of one size are alike, so what the heap places is the histogram of group sizes, exactly as it would place the groups one by one;
of a size with many groups a shard takes a run at a time. Groups then find their shards by their rank among those of the same size.
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from landmark_kkm.session import materialize

#: Bytes that a document takes besides its text.
OVERHEAD = 16
#: Rows that one task numbers.
RANK_ROWS = 200_000
#: Bytes of places up to which they are broadcast.
BROADCAST_BYTES = 64 << 20


def longest_first(sizes: dict[int, int], shards: int) -> list[tuple[int, int, int]]:
    """(size, shard, count): how many groups of each size go to each shard, for a histogram of sizes; equal loads go to the lower shard."""
    heap = [(0, s) for s in range(shards)]
    out = []
    for size in sorted(sizes, reverse=True):
        left, given = sizes[size], [0] * shards
        while left and (heap[0][0] + size, heap[0][1]) < max(heap):  # fill up to the next load
            load, s = heap[0]
            following, other = min(heap[1:3])
            run = min(left, (following - load) // size + 1 if s < other else -(-(following - load) // size))
            given[s] += run
            left -= run
            heapq.heapreplace(heap, (load + size * run, s))
        if rounds := left // shards:  # the loads are so close that each shard takes one in a round
            given = [n + rounds for n in given]
            heap = [(load + size * rounds, s) for load, s in heap]
            left -= rounds * shards
        for _ in range(left):
            load, s = heap[0]
            given[s] += 1
            heapq.heapreplace(heap, (load + size, s))
        out += [(size, s, n) for s, n in enumerate(given) if n]
    return out


def numbered(rows: DataFrame, group: str, order: list, name: str, salts: Column) -> DataFrame:
    """rows with `name`, gapless from 0 in each value of `group`, in no task more than a part of a group.

    salts is the number of parts of a row's group. Rows are numbered inside (group, part), and the counts before each part (a row for each part) are added by a join."""
    salted = rows.withColumn("_salt", F.pmod(F.xxhash64(*order), salts).cast("int"))
    counts = salted.groupBy(group, "_salt").agg(F.count("*").alias("_n"))
    before = counts.withColumn("_before", F.sum("_n").over(Window.partitionBy(group).orderBy("_salt").rowsBetween(Window.unboundedPreceding, -1)))
    before = before.select(F.col(group).alias("_g"), F.col("_salt").alias("_s"), F.coalesce("_before", F.lit(0)).alias("_before"))
    within = salted.withColumn("_rank", F.row_number().over(Window.partitionBy(group, "_salt").orderBy(*order)) - 1)
    joined = within.join(F.broadcast(before), (within[group] == before["_g"]) & (within["_salt"] == before["_s"]))
    return joined.withColumn(name, (F.col("_rank") + F.col("_before")).cast("long")).drop("_salt", "_rank", "_g", "_s", "_before")


def parts_of(count) -> int:
    """Parts of RANK_ROWS rows or so."""
    return max(1, -(-count // RANK_ROWS))


def _places(spark: SparkSession, sizes: dict[int, int], given: list[tuple[int, int, int]]) -> DataFrame:
    """(whole, shards, ends): the shards of the groups of a size, and up to which rank each has them. Broadcast within BROADCAST_BYTES, else met by a shuffle."""
    table = np.array(given, dtype=np.int64).reshape(-1, 3)
    first = np.flatnonzero(np.append(True, table[1:, 0] != table[:-1, 0])) if len(table) else np.zeros(0, np.int64)
    total = np.cumsum(table[:, 2])
    before = np.repeat(np.append(0, total)[first], np.diff(np.append(first, len(table))))
    offsets = pa.array(np.append(first, len(table)).astype(np.int32))
    lists = {"shards": pa.array(table[:, 1].astype(np.int32)), "ends": pa.array(total - before)}
    found = spark.createDataFrame(pa.table({"whole": table[first, 0]} | {k: pa.ListArray.from_arrays(offsets, v) for k, v in lists.items()}))
    return F.broadcast(found) if 12 * len(table) + 32 * len(sizes) <= BROADCAST_BYTES else found


def shard_documents(docs: DataFrame, shards: int = 40, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, size, text_crc32, law, shard, slot, grown_shard) of every row, under the law `bytes`: sizes near equal.

    Equal texts share a shard; a null text counts as an empty one. A group as large as a shard makes its shard the largest, as it may not be split.
    Repeated rows and null ids each keep their row. An empty table gives no rows. Other columns are ignored.

    The driver holds the histogram of group sizes: a row for each size that a group has."""
    if shards < 1:
        raise ValueError("shards must be at least 1")
    spark = docs.sparkSession
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        (F.octet_length(text) + OVERHEAD).cast("long").alias("size"),
        F.crc32(F.encode(text, "UTF-8")).alias("text_crc32"),
        F.xxhash64(text).alias("group"),
    )
    rows = materialize(rows, "sizes")
    groups = materialize(rows.groupBy("group").agg(F.sum("size").alias("whole")), "groups")
    sizes = {r["whole"]: r["count"] for r in groups.groupBy("whole").count().collect()}
    places = _places(spark, sizes, longest_first(sizes, shards))
    large = [(size, parts_of(n)) for size, n in sizes.items() if n > RANK_ROWS]
    if large:
        groups = groups.join(F.broadcast(spark.createDataFrame(large, "whole long, parts int")), "whole", "left").withColumn("parts", F.coalesce("parts", F.lit(1)))
    ranked = numbered(groups, "whole", [F.col("group")], "rank", F.col("parts") if large else F.lit(1))
    met = ranked.select("group", "whole", "rank").join(places, "whole")
    places = met.select("group", F.get("shards", F.size(F.filter("ends", lambda end: end <= F.col("rank")))).alias("shard"))
    placed = rows.join(places, "group").select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard")
    return numbered(placed, "shard", [F.col("doc_id"), F.col("text_crc32")], "slot", F.lit(parts_of(rows.count()))).withColumn("grown_shard", F.lit(None).cast("int"))

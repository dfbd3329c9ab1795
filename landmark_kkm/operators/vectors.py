"""Vectors that leave partitions as a few partial sums, and their merge."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

#: Partitions above which partial sums are merged in two levels.
TWO_LEVELS = 256
#: Rows that are added up at a time: at 500 numbers each they stay in a core's cache.
ROWS = 128
#: Bytes of partial sums that come to the driver as they are, without a shuffle.
GATHERED = 32 << 20

PARTIAL_DDL = "key int, part int, z array<double>, g double, sse double, changed long, far double, far_y array<double>"
_SCHEMA = pa.schema([("key", pa.int32()), ("part", pa.int32()), ("z", pa.list_(pa.float64())), ("g", pa.float64()), ("sse", pa.float64()), ("changed", pa.int64()), ("far", pa.float64()), ("far_y", pa.list_(pa.float64()))])


def matrix_of(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    """A list column of equal lengths as rows of float64, or a packed column as rows of float32."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    n = len(column)
    if pa.types.is_binary(column.type):
        if not n:
            return np.zeros((0, 0), np.float32)
        ends = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + n + 1]
        return np.frombuffer(column.buffers()[2], np.uint8)[ends[0] : ends[-1]].view("<f4").reshape(n, -1)
    values = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return values.reshape(n, -1) if n else np.zeros((0, 0))


def lists_of(rows: np.ndarray, kind: pa.DataType) -> pa.Array:
    """Rows as a list column."""
    n, m = rows.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * m), pa.array(rows.ravel(), kind))


def packed_rows(rows: np.ndarray) -> pa.Array:
    """Rows as a binary column, 4 bytes a number: what the loop reads in each iteration, without a list to take apart."""
    rows = np.ascontiguousarray(rows, "<f4")
    n, m = rows.shape
    return pa.Array.from_buffers(pa.binary(), n, [None, pa.py_buffer(np.arange(n + 1, dtype=np.int32) * 4 * m), pa.py_buffer(rows)])


def _weighted(y: np.ndarray, at: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """The weighted sum of the rows at, in float64: a few rows at a time, so that no copy of a batch is made."""
    total = np.zeros(y.shape[1])
    for i in range(0, len(at), ROWS):
        total += weight[i : i + ROWS] @ y[at[i : i + ROWS]].astype(np.float64, copy=False)
    return total


class Partials:
    """Sums of vectors by key inside a partition; at most one row for each key leaves it. The farthest vector goes along only where it is asked for."""

    def __init__(self, far: bool = False):
        self.held: dict[int, list] = {}
        self.far = far

    def add(self, keys: np.ndarray, y: np.ndarray, weight: np.ndarray, cost: np.ndarray, changed: np.ndarray) -> None:
        order = np.argsort(keys, kind="stable")
        keys, weight, cost, changed = keys[order], weight[order], cost[order], changed[order]
        first = np.flatnonzero(np.append(True, keys[1:] != keys[:-1])) if len(keys) else []
        for a, b in zip(first, [*first[1:], len(keys)]):
            far = int(np.argmax(cost[a:b])) + a
            row = [_weighted(y, order[a:b], weight[a:b]), weight[a:b].sum(), weight[a:b] @ cost[a:b], int(changed[a:b].sum()), cost[far], y[order[far]] if self.far else y[:0, 0]]
            old = self.held.get(int(keys[a]))
            if old:
                row = [old[0] + row[0], old[1] + row[1], old[2] + row[2], old[3] + row[3], *max((old[4:], row[4:]), key=lambda x: x[0])]
            self.held[int(keys[a])] = row

    def batch(self) -> pa.RecordBatch:
        part = TaskContext.get().partitionId() if TaskContext.get() else 0
        rows = [{"key": k, "part": part, "z": z, "g": g, "sse": s, "changed": c, "far": f, "far_y": fy} for k, (z, g, s, c, f, fy) in sorted(self.held.items())]
        return pa.RecordBatch.from_pylist(rows, schema=_SCHEMA)


def _merge(table: pa.Table) -> pa.Table:
    z = matrix_of(table.column("z"))
    far = table.column("far").to_numpy()
    i = int(np.argmax(far))
    row = {"key": table.column("key")[0].as_py(), "part": 0, "z": z.sum(0), "g": float(table.column("g").to_numpy().sum()), "sse": float(table.column("sse").to_numpy().sum()), "changed": int(table.column("changed").to_numpy().sum()), "far": float(far[i]), "far_y": table.column("far_y")[i].as_py()}
    return pa.Table.from_pylist([row], schema=_SCHEMA)


def levels(partitions: int, size: int) -> int:
    """What merged() takes as partitions, where each sends `size` bytes of sums at most: 0 if all of them together are GATHERED or less."""
    return partitions if partitions * size > GATHERED else 0


def _gathered(table: pa.Table) -> list[dict]:
    """One row for each key: sums in the order of the partitions, whatever came first."""
    table = table.sort_by([("key", "ascending"), ("part", "ascending")])
    key, z = table.column("key").to_numpy(), matrix_of(table.column("z"))
    first = np.flatnonzero(np.append(True, key[1:] != key[:-1])) if len(key) else []
    g, sse, changed, far = (table.column(c).to_numpy() for c in ("g", "sse", "changed", "far"))
    found = []
    for a, b in zip(first, [*first[1:], len(key)]):
        i = int(np.argmax(far[a:b])) + a
        found.append({"key": int(key[a]), "part": 0, "z": z[a:b].sum(0), "g": float(g[a:b].sum()), "sse": float(sse[a:b].sum()), "changed": int(changed[a:b].sum()), "far": float(far[i]), "far_y": table.column("far_y")[i].as_py()})
    return found


def merged(partials: DataFrame, partitions: int) -> list:
    """One row for each key, on the driver: as many as there are keys. With many partitions a salted level goes first; with 0 (see levels) the driver adds up."""
    from pyspark.sql import functions as F

    if not partitions:
        return _gathered(partials.toArrow())
    if partitions > TWO_LEVELS:
        salt = F.pmod("part", F.lit(int(partitions**0.5))).alias("salt")
        partials = partials.groupBy("key", salt).applyInArrow(lambda t: _merge(t), PARTIAL_DDL)
    return sorted(partials.groupBy("key").applyInArrow(lambda t: _merge(t), PARTIAL_DDL).collect(), key=lambda r: r["key"])


def summed_by_key(batches: Iterator[pa.RecordBatch], of, far: bool = False) -> Iterator[pa.RecordBatch]:
    """The partials of a partition; of(batch) gives (keys, y, weight, cost, changed)."""
    held = Partials(far)
    for batch in batches:
        if batch.num_rows:
            held.add(*of(batch))
    yield held.batch()

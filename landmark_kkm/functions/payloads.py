"""Instance payloads of a batch: dense rows, sparse rows, or any objects; built from Arrow columns."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Multiply-adds of a matrix product in the time of one pair of sparse entries; pairs that are worked out at a time; rows and features of one product.
PRODUCT = 200
PAIRS = 1 << 18
LAID_OUT = 1024
#: Features up to which places are looked up in a table rather than searched for.
TABLE = 1 << 20


@dataclass
class Dense:
    rows: np.ndarray  # (n, d) float64, or narrowed

    def __len__(self) -> int:
        return len(self.rows)

    def take(self, at) -> Dense:
        return Dense(self.rows[at].astype(np.float64, copy=False))

    def narrowed(self) -> Dense:
        """The same rows in half the bytes, where float32 holds each number exactly; what is taken of them is float64 again."""
        rows = self.rows.astype(np.float32)
        return Dense(rows) if (rows == self.rows).all() else self

    def joined(self, others) -> Dense:
        return Dense(np.concatenate([self.rows, *(o.rows for o in others)])) if others else self

    def dot(self, other: Dense) -> np.ndarray:
        return self.rows.astype(np.float64, copy=False) @ other.rows.T.astype(np.float64, copy=False)

    def norms(self) -> np.ndarray:
        return np.einsum("ij,ij->i", self.rows, self.rows, dtype=np.float64)

    def nbytes(self) -> int:
        return self.rows.nbytes


@dataclass
class Sparse:
    """Rows in compressed form: row i has val[start[i]:start[i + 1]] at idx of the same range."""

    size: int
    start: np.ndarray
    idx: np.ndarray
    val: np.ndarray

    def __len__(self) -> int:
        return len(self.start) - 1

    def take(self, at) -> Sparse:
        at = np.arange(len(self))[at]
        n = np.diff(self.start)[at]
        start = np.append(0, np.cumsum(n))
        pick = np.repeat(self.start[at] - start[:-1], n) + np.arange(start[-1])
        return Sparse(self.size, start, self.idx[pick], self.val[pick])

    def joined(self, others) -> Sparse:
        every = [self, *others]
        start = np.append(0, np.cumsum(np.concatenate([np.diff(p.start) for p in every])))
        return Sparse(max(p.size for p in every), start, np.concatenate([p.idx for p in every]), np.concatenate([p.val for p in every])) if others else self

    def dot(self, other: Sparse) -> np.ndarray:
        """Entries meet those of `other` at the same feature, so time and memory follow the pairs that meet, not `size`, nor features times rows of `other`.
        Features that many rows of both have go through a matrix product instead, some of them at a time."""
        n, l = len(self), len(other)
        out = np.zeros((n, l))
        if not n or not l or not len(other.idx) or not len(self.idx):
            return out
        order = np.argsort(other.idx, kind="stable")
        who, worth = np.repeat(np.arange(l), np.diff(other.start))[order], other.val[order]
        used, first, times = np.unique(other.idx[order], return_index=True, return_counts=True)
        if (most := max(used[-1], self.idx.max())) < TABLE:
            at = np.full(most + 1, -1, np.int32)
            at[used] = np.arange(len(used))
            at = at[self.idx]
            meets = at >= 0
        else:
            at = np.minimum(np.searchsorted(used, self.idx), len(used) - 1)
            meets = used[at] == self.idx
        row = np.repeat(np.arange(n), np.diff(self.start))
        frequent = np.flatnonzero(np.bincount(at[meets], minlength=len(used)) * times * PRODUCT > n * l)
        for f in range(0, len(frequent), LAID_OUT):
            part = frequent[f : f + LAID_OUT]
            place = np.full(len(used), -1)
            place[part] = np.arange(len(part))
            theirs = np.repeat(np.arange(len(used)), times)
            theirs_at = place[theirs]
            right = np.bincount(theirs_at[theirs_at >= 0] * l + who[theirs_at >= 0], worth[theirs_at >= 0], len(part) * l).reshape(len(part), l)
            own = np.where(meets, place[at], -1)
            for r in range(0, n, LAID_OUT):
                lo, hi, rows = self.start[r], self.start[min(r + LAID_OUT, n)], min(LAID_OUT, n - r)
                here = np.flatnonzero(own[lo:hi] >= 0) + lo
                out[r : r + rows] += np.bincount((row[here] - r) * len(part) + own[here], self.val[here], rows * len(part)).reshape(rows, len(part)) @ right
        rare = np.ones(len(used), bool)
        rare[frequent] = False
        pairs = np.where(meets & rare[at], times[at], 0)
        ends = np.append(0, np.cumsum(pairs))[self.start] + np.arange(n + 1) * l
        cut = np.flatnonzero(np.diff(ends[:-1] // PAIRS, prepend=-1))
        for a, b in zip(cut, [*cut[1:], n]):
            lo, hi = self.start[a], self.start[b]
            met = np.flatnonzero(pairs[lo:hi]) + lo
            count = pairs[met]
            pos = np.arange(count.sum()) + np.repeat(first[at[met]] - np.cumsum(count) + count, count)
            key = np.repeat((row[met] - a) * l, count) + who[pos]
            out[a:b] += np.bincount(key, np.repeat(self.val[met], count) * worth[pos], (b - a) * l).reshape(b - a, l)
        return out

    def norms(self) -> np.ndarray:
        return np.bincount(np.repeat(np.arange(len(self)), np.diff(self.start)), weights=self.val * self.val, minlength=len(self))

    def nbytes(self) -> int:
        return self.start.nbytes + self.idx.nbytes + self.val.nbytes


@dataclass
class Objects:
    rows: list

    def __len__(self) -> int:
        return len(self.rows)

    def take(self, at) -> Objects:
        return Objects([self.rows[i] for i in np.arange(len(self.rows))[at]])

    def joined(self, others) -> Objects:
        return Objects([r for p in (self, *others) for r in p.rows]) if others else self

    def nbytes(self) -> int:
        return sum(len(str(r)) for r in self.rows)


Payload = Dense | Sparse | Objects


def from_arrow(column: pa.Array | pa.ChunkedArray) -> Payload:
    """array<number> as Dense, struct(size, idx, val) as Sparse, all else as Objects. Nulls, NaNs and uneven lengths are errors (checked where rows are read, see dataset.validated)."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
        if isinstance(column, pa.ChunkedArray):
            column = column.chunk(0) if column.num_chunks else pa.array([], column.type)
    kind = column.type
    if pa.types.is_list(kind) and (pa.types.is_floating(kind.value_type) or pa.types.is_integer(kind.value_type)):
        if column.null_count:
            raise ValueError("a feature vector is null")
        values = pc.list_flatten(column).to_numpy(zero_copy_only=False).astype(np.float64)
        n = len(column)
        if n and len(values) % n:
            raise ValueError("feature vectors differ in length")
        lengths = pc.list_value_length(column).to_numpy(zero_copy_only=False)
        if n and (lengths != lengths[0]).any():
            raise ValueError("feature vectors differ in length")
        if not np.isfinite(values).all():
            raise ValueError("a feature is null, NaN or infinite")
        return Dense(values.reshape(n, -1) if n else np.zeros((0, 0)))
    if pa.types.is_struct(kind) and {f.name for f in kind} == {"size", "idx", "val"}:
        if column.null_count:
            raise ValueError("a feature vector is null")
        idx, val = column.field("idx"), column.field("val")
        start = np.append(0, np.cumsum(pc.fill_null(pc.list_value_length(idx), 0).to_numpy(zero_copy_only=False))).astype(np.int64)
        size = column.field("size").to_numpy(zero_copy_only=False)
        return Sparse(int(size.max()) if len(size) else 0, start, pc.list_flatten(idx).to_numpy(zero_copy_only=False).astype(np.int64), pc.list_flatten(val).to_numpy(zero_copy_only=False).astype(np.float64))
    return Objects(column.to_pylist())

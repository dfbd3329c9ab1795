"""Bytes, words and batches shared by the corpus operators."""

from __future__ import annotations

import ctypes
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash

#: Word separators of every operator here: space and the ASCII controls 9 to 13, which bytes.split() takes by default.
SEPARATORS = b" \t\n\x0b\x0c\r"


def release() -> None:
    """Give memory that is free back to the system: workers are used again, and what one task had held would count against the next."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc has it
    if trim:
        trim(0)


def as_bytes(column) -> list[bytes]:
    """UTF-8 bytes of a string column, an empty string for null."""
    return [b"" if x is None else x for x in column.cast(pa.binary()).to_pylist()]


def slices(batch: pa.RecordBatch, column: str, limit: int = 8 << 20) -> Iterator[pa.RecordBatch]:
    """The batch cut into runs of rows whose texts hold about `limit` bytes, so that work memory stays bounded."""
    if batch.num_rows == 0:
        return
    size = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
    run = np.cumsum(size.astype(np.int64)) // limit
    cuts = np.flatnonzero(np.diff(run)) + 1
    start = 0
    for stop in [*cuts.tolist(), batch.num_rows]:
        if stop > start:
            yield batch.slice(start, stop - start)
        start = stop


def words_of(text: bytes) -> list[bytes]:
    """Lower-cased (A-Z only) words of a UTF-8 text."""
    return text.lower().split()


def shingle_hashes(words: list[bytes], width: int, seed: int = 42) -> np.ndarray:
    """XXH64 of each run of `width` words joined by a space, repeats included; of all words if there are fewer; none for no words."""
    if not words:
        return np.zeros(0, np.uint64)
    joined = b" ".join(words)
    if len(words) <= width:
        return np.array([xxhash.xxh64_intdigest(joined, seed)], dtype=np.uint64)
    lengths = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(lengths + 1) - 1
    begins = (ends - lengths).tolist()
    digest = xxhash.xxh64_intdigest
    return np.array([digest(joined[a:b], seed) for a, b in zip(begins, ends[width - 1 :].tolist())], dtype=np.uint64)


def mix(x: np.ndarray, salt: int) -> np.ndarray:
    """Another 64-bit hash of a 64-bit hash (splitmix finaliser)."""
    with np.errstate(over="ignore"):
        x = x + np.uint64((0x9E3779B97F4A7C15 * salt) & 0xFFFFFFFFFFFFFFFF)
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


def whole_groups(batches: Iterator[pa.RecordBatch], key: str, rows: int = 200_000) -> Iterator[pa.Table]:
    """Tables of at least `rows` rows that never split a run of equal keys; the input is sorted by key."""
    held: list[pa.RecordBatch] = []
    count = 0
    for batch in batches:
        held.append(batch)
        count += batch.num_rows
        if count < rows:
            continue
        table = pa.Table.from_batches(held)
        keys = table.column(key).to_numpy()
        cut = int(np.flatnonzero(keys != keys[-1])[-1]) + 1 if keys[0] != keys[-1] else 0
        if cut:
            yield table.slice(0, cut)
        rest = table.slice(cut)
        held, count = rest.combine_chunks().to_batches(), rest.num_rows
    if count:
        yield pa.Table.from_batches(held)


@cache
def _codec() -> pa.Codec:
    return pa.Codec("zstd", compression_level=1)


def packed(values: np.ndarray, rising: bool = False) -> bytes:
    """The values as bytes: the first bytes of all, then the second ones, and so on, compressed; for rising keys the steps between them."""
    values = np.diff(values, prepend=np.zeros(1, values.dtype)) if rising else np.ascontiguousarray(values)
    planes = np.ascontiguousarray(values.view(np.uint8).reshape(len(values), -1).T).tobytes()
    return len(planes).to_bytes(8, "little") + _codec().compress(planes, asbytes=True)


def unpacked(data: bytes, kind=np.int64, rising: bool = False) -> np.ndarray:
    planes = _codec().decompress(data[8:], int.from_bytes(data[:8], "little"), asbytes=True)
    values = np.ascontiguousarray(np.frombuffer(planes, np.uint8).reshape(np.dtype(kind).itemsize, -1).T).view(kind).ravel()
    return np.cumsum(values) if rising else values


def joined(parts: list[np.ndarray], kind=np.int64) -> np.ndarray:
    return np.concatenate(parts) if parts else np.zeros(0, kind)

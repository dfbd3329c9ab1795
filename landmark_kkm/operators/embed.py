"""The embedding pass: map-only, landmarks and coefficients in each worker, portions side by side on their row."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from landmark_kkm.functions.kernels import Kernel
from landmark_kkm.functions.payloads import from_arrow
from landmark_kkm.operators.coefficients import CoefficientBlock
from landmark_kkm.operators.vectors import lists_of, packed_rows
from landmark_kkm.session import hold, materialize, ship

#: Bytes of one block and, for "auto", of all blocks that a worker may hold.
MAX_BLOCK_BYTES = 1 << 30
FUSED_BYTES = 512 << 20
#: Rows that are evaluated at a time: rows times landmarks times 8 bytes stays near 32 MB.
CELLS = 1 << 22


def embedded(x: pa.Array, blocks: list[CoefficientBlock], kernel: Kernel, kind: type = np.float64) -> np.ndarray:
    """Embeddings of a column of payloads, portion by portion. Only a part of the rows is taken apart at a time, and what is kept of it is the result."""
    out = np.zeros((len(x), sum(len(b.R) for b in blocks)), kind)
    step = max(1, CELLS // max(len(b.landmarks) for b in blocks))
    for at in range(0, len(x), step):
        part = from_arrow(x.slice(at, step))
        to = 0
        for b in blocks:
            out[at : at + step, to : to + len(b.R)] = b.apply(part, kernel)
            to += len(b.R)
    return out


def _portions(batches: Iterator[pa.RecordBatch], held, name: str, keep: list[str], kind: str) -> Iterator[pa.RecordBatch]:
    blocks, kernel = held.value
    for batch in batches:
        y = embedded(batch.column("x"), blocks, kernel, np.float32 if kind == "packed" else np.float64)
        y = packed_rows(y) if kind == "packed" else lists_of(y, pa.float32() if kind == "float" else pa.float64())
        yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), y], names=[*keep, name])


def _pass(ds: DataFrame, blocks: list[CoefficientBlock], kernel: Kernel, name: str, keep: list[str], kind: str) -> DataFrame:
    held = hold(ds.sparkSession, (blocks, kernel))
    of = T.BinaryType() if kind == "packed" else T.ArrayType(T.FloatType() if kind == "float" else T.DoubleType(), False)
    schema = T.StructType([ds.schema[c] for c in keep] + [T.StructField(name, of)])
    return ds.mapInArrow(lambda it: _portions(it, held, name, keep, kind), schema)


def embed(ds: DataFrame, blocks: list[CoefficientBlock], kernel: Kernel, mode: str = "auto", kind: str = "float", max_block_bytes: int = MAX_BLOCK_BYTES) -> DataFrame:
    """ds without x, with y. No row is shuffled in any mode.

    "fused" holds all blocks in one pass. "rounds" is one narrow step for each block and a concatenation (all steps run in one stage, so this shows the
    structure but bounds no memory). "staged" writes each portion to the shared folder before the next block is loaded, so that a worker holds one block.
    "auto" fuses where the blocks fit together. kind is that of y: lists of "float" or "double", or "packed" bytes of floats, which the loop reads fastest."""
    ship(ds.sparkSession)
    sizes = [b.nbytes for b in blocks]
    if max(sizes) > max_block_bytes:
        raise MemoryError(f"a block takes {max(sizes)} bytes, over the bound of {max_block_bytes}: use more blocks")
    if mode == "auto":
        mode = "fused" if sum(sizes) <= FUSED_BYTES else "staged"
    keep = [c for c in ds.columns if c != "x"]
    if mode == "fused":
        return _pass(ds, blocks, kernel, "y", keep, kind)
    if mode not in ("rounds", "staged"):
        raise ValueError("mode is auto, fused, rounds or staged")
    names = [f"y_{b.block}" for b in blocks]
    for name, block in zip(names, blocks):
        ds = _pass(ds, [block], kernel, name, [c for c in ds.columns], kind)
        if mode == "staged":
            ds = materialize(ds, "portion")
    return ds.select(*keep, F.concat(*names).alias("y"))

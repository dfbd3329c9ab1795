"""Rules that pick a plan from sizes, and checks of the plan that came out."""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import DataFrame

from landmark_kkm.operators.coefficients import CoefficientBlock

SPLIT_BYTES = 1 << 30


@dataclass(frozen=True)
class Scale:
    """n rows of `row_bytes` each, l landmarks of d numbers, m dimensions, k clusters, `passes` iterations."""

    n: int
    row_bytes: int
    l: int
    d: int
    m: int
    k: int
    passes: int = 20


def store_embedding(s: Scale, read_bytes_s: float = 200e6, flops_s: float = 10e9) -> bool:
    """Whether to store y (4 m bytes written and read again in each pass) rather than evaluate it in each pass (l (d + m) multiply-adds and the input read)."""
    stored = s.l * (s.d + s.m) * 2 / flops_s + s.row_bytes / read_bytes_s + (s.passes + 1) * 4 * s.m / read_bytes_s
    anew = s.passes * (s.l * (s.d + s.m) * 2 / flops_s + s.row_bytes / read_bytes_s)
    return stored <= anew


def embed_mode(blocks: list[CoefficientBlock], worker_bytes: int) -> str:
    return "fused" if sum(b.nbytes for b in blocks) <= worker_bytes else "staged"


def embed_partitions(s: Scale, split_bytes: int = SPLIT_BYTES) -> int:
    """Splits of about split_bytes: large ones, as each partition sends k sums in each iteration."""
    return max(1, -(-s.n * s.row_bytes // split_bytes))


def iteration_shuffle_bytes(s: Scale, split_bytes: int = SPLIT_BYTES) -> int:
    return embed_partitions(s, split_bytes) * s.k * (s.m + 1) * 8


def explained(df: DataFrame) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def exchanges(df: DataFrame) -> int:
    """Shuffles in the physical plan."""
    tree = df._jdf.queryExecution().executedPlan().toString()
    return len(re.findall(r"(?<!Broadcast)\bExchange\b", tree))


def read_columns(df: DataFrame) -> list[set[str]]:
    """Columns that each Parquet scan reads."""
    return [set(re.findall(r"(\w+):", s)) for s in re.findall(r"ReadSchema: struct<(.*)>", explained(df))]


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[(.*)\]", explained(df))


def python_stages(df: DataFrame) -> int:
    return len(re.findall(r"MapInArrow|MapInPandas|ArrowEvalPython|BatchEvalPython|FlatMapGroups", df._jdf.queryExecution().executedPlan().toString()))

"""What rows of a dataset are: an id, a payload, and perhaps a weight and a class."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


@dataclass(frozen=True)
class DatasetSpec:
    id_col: str = "id"
    feature_col: str = "x"
    weight_col: str | None = None
    label_col: str | None = None

    def select(self, df: DataFrame) -> DataFrame:
        """(id, x[, weight][, cls]), checked against the schema."""
        missing = [c for c in (self.id_col, self.feature_col, self.weight_col, self.label_col) if c and c not in df.columns]
        if missing:
            raise ValueError(f"no such column: {', '.join(missing)}")
        kind = df.schema[self.id_col].dataType
        if not isinstance(kind, T.IntegralType):
            raise TypeError(f"{self.id_col} must be an integer column, not {kind.simpleString()}")
        columns = [F.col(self.id_col).cast("long").alias("id"), F.col(self.feature_col).alias("x")]
        if self.weight_col:
            columns.append(F.col(self.weight_col).cast("double").alias("weight"))
        if self.label_col:
            columns.append(F.col(self.label_col).cast("string").alias("cls"))
        return df.select(*columns)


def is_dense(ds: DataFrame) -> bool:
    kind = ds.schema["x"].dataType
    return isinstance(kind, T.ArrayType) and isinstance(kind.elementType, T.NumericType)


def bad_vector() -> F.Column:
    """Whether x is null or has a null or NaN (dense vectors)."""
    return F.col("x").isNull() | F.exists("x", lambda v: v.isNull() | F.isnan(v.cast("double")))


def validated(ds: DataFrame, on_invalid: str = "raise") -> DataFrame:
    """Dense rows that are null or hold nulls or NaNs: an error in the task that reads them, or left out (on_invalid="skip")."""
    if on_invalid not in ("raise", "skip"):
        raise ValueError("on_invalid is raise or skip")
    bad = bad_vector() if is_dense(ds) else F.col("x").isNull()
    if on_invalid == "skip":
        return ds.filter(~bad)
    message = F.concat(F.lit("invalid features in row "), F.coalesce(F.col("id").cast("string"), F.lit("null")))
    return ds.withColumn("x", F.when(bad, F.raise_error(message).cast(ds.schema["x"].dataType)).otherwise(F.col("x")))


def profile(ds: DataFrame) -> dict:
    """One aggregate job: rows, least and greatest length, invalid rows."""
    size = F.size("x") if is_dense(ds) else F.lit(None).cast("int")
    bad = bad_vector() if is_dense(ds) else F.col("x").isNull()
    row = ds.agg(F.count("*").alias("n"), F.min(size).alias("d_min"), F.max(size).alias("d_max"), F.count_if(bad).alias("invalid")).first()
    return row.asDict()


def scale_features(ds: DataFrame, how: str, factor: float = 1.0) -> DataFrame:
    """x of dense rows rescaled: "factor", "unit", "zscore" or "minmax" (over all rows, one aggregate of d values)."""
    from landmark_kkm.functions import columns as C

    if how == "factor":
        return ds.withColumn("x", C.scaled(F.col("x"), factor))
    if how == "unit":
        return ds.withColumn("x", C.unit(F.col("x")))
    if how not in ("zscore", "minmax"):
        raise ValueError("how is factor, unit, zscore or minmax")
    cells = ds.select(F.posexplode(C.as_doubles(F.col("x"))).alias("p", "v")).groupBy("p")
    if how == "zscore":
        stats = cells.agg(F.avg("v").alias("at"), F.stddev_pop("v").alias("by"))
    else:
        stats = cells.agg(F.min("v").alias("at"), (F.max("v") - F.min("v")).alias("by"))
    found = sorted(stats.collect())
    at = F.array(*[F.lit(r["at"]) for r in found])
    by = F.array(*[F.lit(r["by"] if r["by"] else 1.0) for r in found])
    return ds.withColumn("x", F.zip_with(F.zip_with(C.as_doubles(F.col("x")), at, lambda v, a: v - a), by, lambda v, b: v / b))

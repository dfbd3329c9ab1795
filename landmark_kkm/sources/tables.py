"""Reading and writing: the given tables, other formats, models and results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from landmark_kkm.session import read_table, spread

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str, parallel: bool = False) -> DataFrame:
    """A table with zoneless timestamps cast to timestamps, which watermarks ask for (the session's zone should be UTC). parallel deals small files over all cores."""
    df = read_table(spark, sf_dir, name)
    for f in df.schema.fields:
        if isinstance(f.dataType, T.TimestampNTZType):
            df = df.withColumn(f.name, F.col(f.name).cast("timestamp"))
    return spread(df) if parallel else df


def register_views(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = TABLES) -> None:
    for name in names:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def read(spark: SparkSession, path: str, kind: str = "parquet", schema: str | T.StructType | None = None, **options) -> DataFrame:
    """parquet, orc, csv, json or libsvm. A libsvm file gives (id, x, cls), x sparse; ids are the rows' numbers within the read."""
    reader = spark.read.options(**options)
    if schema is not None:
        reader = reader.schema(schema)
    if kind == "libsvm":
        return from_libsvm(spark.read.format("libsvm").options(**options).load(path))
    return reader.format(kind).load(path)


def from_libsvm(df: DataFrame) -> DataFrame:
    """(label, features) as (id, x, cls)."""
    from pyspark.ml.functions import vector_to_array

    dense = df.select(F.monotonically_increasing_id().alias("id"), vector_to_array("features").alias("v"), F.col("label").cast("string").alias("cls"))
    cells = F.filter(F.transform("v", lambda v, i: F.struct(i.cast("int").alias("i"), v.cast("float").alias("v"))), lambda c: c["v"] != 0)
    return dense.select("id", F.struct(F.size("v").alias("size"), F.transform(cells, lambda c: c["i"]).alias("idx"), F.transform(cells, lambda c: c["v"]).alias("val")).alias("x"), "cls")


def write(df: DataFrame, path: str, kind: str = "parquet", mode: str = "error", partition_by: tuple[str, ...] = (), buckets: int = 0, bucket_by: str = "id", name: str | None = None) -> None:
    """Files at a path, or (name) a table, bucketed where asked; "noop" forces a plan and writes nothing."""
    if kind == "noop":
        df.write.format("noop").mode("overwrite").save()
        return
    writer = df.write.mode(mode).format(kind)
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    if buckets:
        if not name:
            raise ValueError("only tables can be bucketed")
        writer.bucketBy(buckets, bucket_by).sortBy(bucket_by).option("path", path).saveAsTable(name)
    elif name:
        writer.option("path", path).saveAsTable(name)
    else:
        writer.save(path)


def to_ml_vector(df: DataFrame, column: str = "x", to: str = "features") -> DataFrame:
    """A dense or sparse payload as the machine-learning library's vector."""
    from pyspark.ml.functions import array_to_vector

    if isinstance(df.schema[column].dataType, T.ArrayType):
        return df.withColumn(to, array_to_vector(F.col(column).cast("array<double>")))
    from pyspark.ml.linalg import Vectors, VectorUDT

    as_sparse = F.udf(lambda x: Vectors.sparse(x["size"], x["idx"], x["val"]), VectorUDT())
    return df.withColumn(to, as_sparse(column))

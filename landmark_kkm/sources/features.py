"""Datasets (id, x[, cls]) from the given tables; all in DataFrame functions."""

from __future__ import annotations

from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from landmark_kkm.functions import columns as C
from landmark_kkm.operators.vectors import lists_of
from landmark_kkm.session import keep, ship
from landmark_kkm.sources.tables import table

# Categories of the one-hot features, in order.
RETURN_FLAGS = ("A", "N", "R")
LINE_STATUS = ("F", "O")
ORDER_STATUS = ("F", "O", "P")


#: Tasks that the pairs of one hour are dealt over.
SALTS = 4


def hash_id(*columns: str) -> Column:
    """60 bits of md5 over integer columns joined by a colon."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", *[F.col(c).cast("string") for c in columns])), 1, 15), 16, 10).cast("long")


def dense(spark: SparkSession, sf_dir: str, factor: float = 1.0) -> DataFrame:
    """embeddings: 64 numbers, class label."""
    rows = table(spark, sf_dir, "embeddings", parallel=True)
    x = C.as_doubles(F.col("embedding"))
    return rows.select(F.col("vec_id").alias("id"), (C.scaled(x, factor) if factor != 1.0 else x).alias("x"), F.col("label").cast("string").alias("cls"))


def _values(df: DataFrame, column: str) -> list:
    return sorted(r[0] for r in df.select(column).distinct().filter(F.col(column).isNotNull()).collect())


def _one_hot(column: str, values) -> list[Column]:
    return [F.when(F.col(column) == v, 1.0).otherwise(0.0) for v in values]


def multivariate_parts(spark: SparkSession, sf_dir: str, wide: bool = False) -> tuple[DataFrame, list[Column]]:
    """The joined order lines, and their feature columns: 13 numeric, 29 one-hot and 12 order months; wide adds 25 brands and 25 nations."""
    t = lambda name, **k: table(spark, sf_dir, name, **k)
    nation = t("nation").join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))
    supplier = t("supplier").join(F.broadcast(nation), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "s_acctbal", "n_name", "r_name")
    customer = t("customer").select("c_custkey", "c_acctbal", "c_mktsegment")
    orders = t("orders").join(customer, F.col("o_custkey") == F.col("c_custkey"))
    part = t("part").select("p_partkey", "p_brand", "p_type", "p_size", "p_retailprice")
    rows = t("lineitem", parallel=True).join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(part, F.col("l_partkey") == F.col("p_partkey")).join(supplier, F.col("l_suppkey") == F.col("s_suppkey"))
    number = lambda c: F.col(c).cast("double")
    numeric = [number(c) for c in ("l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_linenumber", "o_totalprice", "p_size", "p_retailprice", "s_acctbal", "c_acctbal")]
    numeric += [F.datediff("l_shipdate", "o_orderdate").cast("double"), F.year("o_orderdate").cast("double"), F.dayofweek("o_orderdate").cast("double")]
    hot = _one_hot("l_returnflag", RETURN_FLAGS) + _one_hot("l_linestatus", LINE_STATUS) + _one_hot("o_orderstatus", ORDER_STATUS)
    hot += _one_hot("o_orderpriority", _values(t("orders"), "o_orderpriority")) + _one_hot("c_mktsegment", _values(t("customer"), "c_mktsegment"))
    hot += _one_hot("p_type", _values(t("part"), "p_type")) + _one_hot("r_name", _values(t("region"), "r_name"))
    hot += [F.when(F.month("o_orderdate") == m, 1.0).otherwise(0.0) for m in range(1, 13)]
    if wide:
        hot += _one_hot("p_brand", _values(t("part"), "p_brand")) + _one_hot("n_name", _values(t("nation"), "n_name"))
    return rows, numeric + hot


def multivariate(spark: SparkSession, sf_dir: str, wide: bool = False, scaled: bool = True) -> DataFrame:
    """Order lines with their order, part, supplier and customer: 54 (wide: 104) numbers; the class is the part's type (wide: brand and type).

    scaled gives z-scores over all rows, from one aggregate job of two numbers for each feature."""
    rows, features = multivariate_parts(spark, sf_dir, wide)
    cls = F.concat_ws("|", "p_brand", "p_type") if wide else F.col("p_type")
    rows = rows.select(hash_id("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey").alias("id"), F.array(*features).alias("x"), cls.alias("cls"))
    if not scaled:
        return rows
    m = len(features)
    stats = rows.agg(*[F.avg(F.col("x")[i]).alias(f"a{i}") for i in range(m)], *[F.stddev_pop(F.col("x")[i]).alias(f"s{i}") for i in range(m)]).first()
    at, by = [stats[f"a{i}"] or 0.0 for i in range(m)], [stats[f"s{i}"] or 1.0 for i in range(m)]
    return rows.withColumn("x", F.array(*[(F.col("x")[i] - at[i]) / by[i] for i in range(m)]))


def behaviour(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers with the map of what they spent by brand; the class is the market segment. Customers without an order have an empty map."""
    t = lambda name, **k: table(spark, sf_dir, name, **k)
    lines = t("lineitem", parallel=True).select("l_orderkey", "l_partkey", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("spent"))
    spent = lines.join(t("part").select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey")).join(t("orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    cells = spent.groupBy("o_custkey", "p_brand").agg(F.sum("spent").alias("spent"))
    maps = cells.groupBy("o_custkey").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("p_brand", "spent")))).alias("x"))
    empty = F.create_map().cast("map<string,double>")
    return t("customer").join(maps, F.col("c_custkey") == F.col("o_custkey"), "left").select(F.col("c_custkey").alias("id"), F.coalesce("x", empty).alias("x"), F.col("c_mktsegment").alias("cls"))


def users(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users with counts of their event types (by name), of events by hour, and the mean value."""
    events = table(spark, sf_dir, "events", parallel=True)
    kinds = _values(events, "event_type")
    features = [F.count_if(F.col("event_type") == k).cast("double") for k in kinds] + [F.count_if(F.hour("ts") == h).cast("double") for h in range(24)] + [F.coalesce(F.avg("value"), F.lit(0.0))]
    return events.groupBy(F.col("user_id").alias("id")).agg(F.array(*features).alias("x"), F.max_by("event_type", F.struct("ts", "event_id")).alias("cls"))


def gram_counts(texts: list[str | None], size: int, n: int = 3) -> np.ndarray:
    """Counts of each text's lower-cased character n-grams by bucket, their CRC-32 modulo size; a text shorter than n is one gram, an empty one too."""
    out = np.zeros((len(texts), size))
    for row, text in enumerate(texts):
        text = (text or "").lower()
        points = np.frombuffer(text.encode("utf-32-le", "replace"), np.uint32).astype(np.int64)
        if len(points) < n or n > 3:
            grams = [text[i : i + n] for i in range(max(1, len(text) - n + 1))]
            times = np.ones(len(grams))
        else:
            key = np.zeros(len(points) - n + 1, np.int64)
            for i in range(n):
                key = key << 21 | points[i : len(key) + i]
            key, times = np.unique(key, return_counts=True)
            grams = ["".join(chr(k >> 21 * (n - 1 - i) & 0x1FFFFF) for i in range(n)) for k in key.tolist()]
        np.add.at(out[row], [crc32(g.encode("utf-8", "replace")) % size for g in grams], times)
    return out


def text_grams(spark: SparkSession, sf_dir: str, size: int = 512, n: int = 3) -> DataFrame:
    """documents as square-root counts of lower-cased character n-grams hashed to `size` buckets, of unit length; the class is lang.

    One map over Arrow batches: a text's grams are counted where it is, and nothing is shuffled."""
    ship(spark)
    docs = table(spark, sf_dir, "documents", parallel=True).select(F.col("doc_id").alias("id"), F.col("text"), F.col("lang").alias("cls"))

    def rows(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                x = np.sqrt(gram_counts(part.column("text").to_pylist(), size, n))
                x /= np.sqrt((x * x).sum(1, keepdims=True))
                yield pa.RecordBatch.from_arrays([part.column("id"), lists_of(x, pa.float64()), part.column("cls")], names=["id", "x", "cls"])

    return docs.mapInArrow(rows, "id long, x array<double>, cls string")


def text_sparse(spark: SparkSession, sf_dir: str, bits: int = 16, kept: bool = False) -> DataFrame:
    """documents as TF-IDF of words hashed to 2^bits buckets, sparse and of unit length; the class is lang, and source goes along.

    What is shuffled is the number of documents of each bucket (2^bits at most, which the driver broadcasts); a document's own counts are taken where it is.
    A document without words has a vector without entries. kept has texts split once, not twice: the buckets of their words are persisted until release()."""
    ship(spark)
    docs = table(spark, sf_dir, "documents", parallel=True)
    words = F.filter(F.split(F.lower(F.coalesce("text", F.lit(""))), "[^\\p{L}\\p{N}]+"), lambda w: w != "")
    buckets = F.transform(words, lambda w: F.pmod(F.crc32(F.encode(w, "UTF-8")), F.lit(1 << bits)).cast("int"))
    hashed = docs.select(F.col("doc_id").alias("id"), F.col("lang").alias("cls"), "source", buckets.alias("b"))
    if kept:
        docs = hashed = keep(hashed)
    n, found = docs.count(), hashed.select(F.explode(F.array_distinct("b")).alias("b")).groupBy("b").count().toArrow()
    idf = np.zeros(1 << bits)
    idf[found.column("b").to_numpy()] = np.log((n + 1.0) / (found.column("count").to_numpy() + 1.0)) + 1.0
    known = spark.sparkContext.broadcast(idf)

    def weighed(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 2048):
                part = batch.slice(at, 2048)
                lists, rows = part.column("b"), part.num_rows
                key = np.repeat(np.arange(rows), lists.value_lengths().to_numpy()) << bits | lists.flatten().to_numpy()
                key, times = np.unique(key, return_counts=True)
                row, bucket = key >> bits, key & (1 << bits) - 1
                v = times * known.value[bucket]
                v /= np.sqrt(np.bincount(row, v * v, rows))[row]
                ends = pa.array(np.append(0, np.cumsum(np.bincount(row, minlength=rows))).astype(np.int32))
                x = pa.StructArray.from_arrays(
                    [pa.array(np.full(rows, 1 << bits, np.int32)), pa.ListArray.from_arrays(ends, pa.array(bucket.astype(np.int32))), pa.ListArray.from_arrays(ends, pa.array(v.astype(np.float32)))], ["size", "idx", "val"]
                )
                yield pa.RecordBatch.from_arrays([part.column("id"), x, part.column("cls"), part.column("source")], names=["id", "x", "cls", "source"])

    return hashed.mapInArrow(weighed, "id long, x struct<size: int, idx: array<int>, val: array<float>>, cls string, source string")


def link_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """pages with the set of their link targets."""
    pages = table(spark, sf_dir, "pages", parallel=True)
    return pages.select(F.col("page_id").alias("id"), F.array_sort(F.array_distinct(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1))).alias("x"))


def neighbours(spark: SparkSession, sf_dir: str, of: DataFrame) -> DataFrame:
    """Users with the map of those of the users `of` (id) they share hours with, two or more, to the number of those hours, and their own id under -1: similarities for the precomputed kernel."""
    hours = _hours(spark, sf_dir)
    theirs = hours.join(F.broadcast(of.select(F.col("id").alias("user_id"))), "user_id", "left_semi").select(F.col("user_id").alias("dst"), "h")
    cells = hours.withColumnRenamed("user_id", "id").join(F.broadcast(theirs), "h").filter("id <> dst").groupBy("id", "dst").agg(F.count("*").cast("double").alias("weight")).filter("weight >= 2")
    cells = cells.groupBy("id").agg(F.collect_list(F.struct("dst", "weight")).alias("c"))
    own = F.array(F.struct(F.lit(-1).cast("long").alias("dst"), F.col("id").cast("double").alias("weight")))
    return hours.select(F.col("user_id").alias("id")).distinct().join(cells, "id", "left").select("id", F.map_from_entries(F.concat(own, F.coalesce("c", F.slice(own, 2, 1)))).alias("x"))


def _hours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").select(F.col("user_id").cast("long").alias("user_id"), F.date_trunc("hour", "ts").alias("h")).distinct()


def user_hours(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, x): users with the hours in which they have events, as the bits of a binary value, an hour at the same place in all."""
    ship(spark)
    hour = (F.unix_timestamp("h") / 3600).cast("int")
    hours = _hours(spark, sf_dir).select(F.col("user_id").alias("id"), hour.alias("h"))
    least, most = hours.agg(F.min("h"), F.max("h")).first()
    size = most - least + 1 if least is not None else 0

    def packed(batches):
        for batch in batches:
            lists = batch.column("h")
            bits = np.zeros((batch.num_rows, size), np.uint8)
            bits[np.repeat(np.arange(batch.num_rows), lists.value_lengths().to_numpy()), lists.flatten().to_numpy()] = 1
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array([r.tobytes() for r in np.packbits(bits, axis=1)], pa.binary())], names=["id", "x"])

    return hours.groupBy("id").agg(F.collect_list(F.col("h") - least).alias("h")).mapInArrow(packed, "id long, x binary")


def strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Conversation turns as strings; the class is the role."""
    return table(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), F.col("text").alias("x"), F.col("role").alias("cls"))


def event_graph(spark: SparkSession, sf_dir: str, least: int = 2) -> DataFrame:
    """(src, dst, weight): users by the number of hours in which both have events, `least` or more.

    The edges are the result, so an hour with u users makes u * u / 2 of them; its pairs are dealt over SALTS tasks, and are added up before they are shuffled."""
    hours = table(spark, sf_dir, "events").select("user_id", F.date_trunc("hour", "ts").alias("h")).distinct()
    a = hours.select(F.col("user_id").alias("src"), "h", F.pmod(F.xxhash64("user_id"), F.lit(SALTS)).alias("salt"))
    b = hours.select(F.col("user_id").alias("dst"), "h", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
    return a.join(b, ["h", "salt"]).filter("src < dst").groupBy("src", "dst").agg(F.count("*").alias("weight")).filter(F.col("weight") >= least)


def labelled_text(spark: SparkSession, sf_dir: str, **how) -> DataFrame:
    """text_grams with quality and toxic, for documents that have labels."""
    return text_grams(spark, sf_dir, **how).join(table(spark, sf_dir, "labels").select(F.col("doc_id").alias("id"), "quality", "toxic"), "id")

"""Threshold-scaled sketches of word shingles, in DataFrame functions alone."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

WIDTH = 5
#: One shingle hash in SCALE is kept; texts of at most WHOLE shingles keep all, that is one in 1.
SCALE, WHOLE = 4, 64
#: Documents in a run that one task orders, and the most runs (their first ids are broadcast: 24 bytes each).
RUN_DOCS, MOST_RUNS = 1000, 1 << 20
#: Cuts between runs that are quantiles of the ids; beyond, runs between two quantiles are cut evenly.
QUANTILES = 4096
#: Text bytes that one task orders.
TASK_BYTES = 32 << 20
LOWEST = -(1 << 63)


def word_hashes(text: Column) -> Column:
    """XXH64 of each lower-cased word; words are parted by space and the ASCII controls 9 to 13."""
    words = F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), "[\\x20\\x09-\\x0D]+"), lambda w: w != "")
    return F.transform(words, lambda w: F.xxhash64(w))


def _below(hashes: Column, scale: int) -> Column:
    return hashes if scale == 1 else F.filter(hashes, lambda h: h < F.lit(LOWEST + (1 << 64) // scale))


def sketch(hashes: Column, width: int = WIDTH, scale: int = SCALE, whole: int = WHOLE) -> Column:
    """(scale, hashes): the sorted distinct shingle hashes below the fraction 1/scale of the hash range, or all (scale 1) of a text of at most `whole` shingles.

    Fewer words than width are one shingle, no words none. Sketches are compared and merged at the larger of their scales, so any two can be."""
    n = F.size(hashes)
    runs = F.transform(F.sequence(F.lit(0), F.greatest(n - width, F.lit(0))), lambda i: F.xxhash64(*[F.get(hashes, i + j) for j in range(width)]))
    runs = F.when(n == 0, F.array().cast("array<bigint>")).otherwise(runs)
    short = n - width < whole
    kept = F.when(short, runs).otherwise(_below(runs, scale))
    return F.struct(F.when(short, F.lit(1)).otherwise(F.lit(scale)).alias("scale"), F.array_sort(F.array_distinct(kept)).alias("hashes"))


def _common(a: Column, b: Column, scale: int) -> tuple[Column, Column]:
    """The hashes of both sketches at the larger of their scales."""
    at = lambda x, y: F.when((x["scale"] == 1) & (y["scale"] > 1), _below(x["hashes"], scale)).otherwise(x["hashes"])
    return at(a, b), at(b, a)


def likeness(a: Column, b: Column, scale: int = SCALE) -> Column:
    """Estimated similarity of the shingle sets (shared over all), 1 for two texts without words."""
    x, y = _common(a, b, scale)
    shared = F.size(F.array_intersect(x, y))
    every = F.size(x) + F.size(y) - shared
    return F.when(F.size(a["hashes"]) + F.size(b["hashes"]) == 0, F.lit(1.0)).when(every == 0, F.lit(0.0)).otherwise(shared / every)


def containment(a: Column, b: Column, scale: int = SCALE) -> Column:
    """Estimated share of a's shingles that b has, 1 for a text a without words."""
    x, y = _common(a, b, scale)
    return F.when(F.size(a["hashes"]) == 0, F.lit(1.0)).when(F.size(x) == 0, F.lit(0.0)).otherwise(F.size(F.array_intersect(x, y)) / F.size(x))


def merged(sketches: Column, scale: int = SCALE) -> Column:
    """Aggregate: the sketch of all the shingle sets together, at the largest scale among them."""
    every = F.array_distinct(F.flatten(F.collect_set(sketches["hashes"])))
    most = F.max(sketches["scale"])
    return F.struct(most.alias("scale"), F.array_sort(F.when(most > 1, _below(every, scale)).otherwise(every)).alias("hashes"))


def as_string(sketch: Column) -> Column:
    """The fingerprint: the scale, and base64 of the hashes, 8 bytes each, on one line."""
    joined = F.array_join(F.transform(sketch["hashes"], lambda h: F.lpad(F.hex(h), 16, "0")), "")
    return F.concat_ws(":", sketch["scale"].cast("string"), F.translate(F.base64(F.unhex(joined)), "\r\n", ""))


def sketches(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH, scale: int = SCALE) -> DataFrame:
    """(doc_id, sketch) of every row."""
    rows = docs.select(F.col(id_col).alias("doc_id"), word_hashes(F.col(text_col)).alias("_h"))
    return rows.select("doc_id", sketch(F.col("_h"), width, scale).alias("sketch"))


def _runs(docs: DataFrame, count: int) -> Column:
    """A run number that rises with doc_id: quantiles of the ids, each cut evenly where there are more runs, so that no run holds many rows. Null ids come in the lowest run."""
    runs = max(1, min(MOST_RUNS, count // RUN_DOCS))
    points = min(QUANTILES, runs)
    fine = -(-runs // points)
    cuts = docs.select(F.col("doc_id").cast("double").alias("d")).approxQuantile("d", [i / points for i in range(points + 1)], 1 / (4 * points))
    cuts = sorted(set(cuts)) or [0.0]
    step = max(1, round(len(cuts) ** 0.5))
    groups = [cuts[i : i + step] for i in range(0, len(cuts), step)]
    heads, nested = F.array(*[F.lit(g[0]) for g in groups]), F.array(*[F.array(*map(F.lit, g)) for g in groups])
    x = F.col("doc_id").cast("double")
    group = F.size(F.filter(heads, lambda c: c <= x)) - 1
    own = F.get(nested, group)
    place = F.size(F.filter(own, lambda c: c <= x)) - 1
    low, high = F.get(own, place), F.coalesce(F.get(own, place + 1), F.get(heads, group + 1))
    inside = F.coalesce(F.floor((x - low) / (high - low) * fine), F.lit(0))
    inside = F.greatest(F.lit(0), F.least(F.lit(fine - 1), inside))
    return F.when(x.isNull() | (group < 0), F.lit(-1)).otherwise((group * step + place) * fine + inside).cast("long")


def edited_pairs(docs: DataFrame, width: int = WIDTH, scale: int = SCALE) -> DataFrame:
    """(doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next, kept) of every document.

    The edited text has its last floor(n_chars / 2) code points replaced by as many (or all) of the next document's first, in descending doc_id,
    after the last the first. Null texts are empty. Rows that share a doc_id come in the order of a text hash, null ids last; a single row is its own
    next. An empty table gives no rows. Texts are shuffled once, by runs of ids; the first row of the following run goes along as a ghost."""
    base = docs.select("doc_id", F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    count, size = base.agg(F.count("*"), F.sum(F.octet_length("text"))).first()
    rows = base.select("doc_id", "text", F.xxhash64("text").alias("tie"), _runs(base, count).alias("run"))
    heads = rows.groupBy("run").agg(F.max(F.struct(F.coalesce("doc_id", F.lit(LOWEST)).alias("id"), F.col("tie"))).alias("head"), F.max("doc_id").alias("real")).orderBy(F.desc("run")).collect()
    spark = docs.sparkSession
    ghosts = [(heads[i - 1]["run"], h["real"], h["head"]["tie"]) for i, h in enumerate(heads)]
    table = F.broadcast(spark.createDataFrame(ghosts, "_to long, _id long, _tie long"))
    ghost = rows.join(table, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("tie") == F.col("_tie"))).select("doc_id", "text", "tie", F.col("_to").alias("run"), F.lit(1).alias("ghost"))
    both = rows.withColumn("ghost", F.lit(0)).unionByName(ghost)
    tasks = max(spark.sparkContext.defaultParallelism, -(-(size or 0) // TASK_BYTES))
    both = both.repartition(tasks, "run").withColumn("_h", word_hashes(F.col("text")))  # sketches are made after the shuffle, so that texts alone move
    both = both.select("doc_id", "text", "tie", "run", "ghost", sketch(F.col("_h"), width, scale).alias("sketch"))
    order = Window.partitionBy("run").orderBy("ghost", F.desc_nulls_last("doc_id"), F.desc("tie"))
    led = both.withColumn("next", F.lead(F.struct("text", "sketch")).over(order)).filter("ghost = 0")
    n = F.char_length("text")
    half = F.floor(n / 2).cast("int")
    led = led.withColumn("edited", F.concat(F.substring("text", F.lit(1), n - half), F.substring(F.col("next.text"), F.lit(1), half)))
    led = led.withColumn("_h", word_hashes(F.col("edited"))).withColumn("edited_sketch", sketch(F.col("_h"), width, scale))
    return led.select(
        "doc_id",
        n.cast("long").alias("n_chars"),
        F.sha2(F.encode("edited", "UTF-8"), 256).alias("edited_sha256"),
        as_string(F.col("sketch")).alias("fingerprint"),
        as_string(F.col("edited_sketch")).alias("edited_fingerprint"),
        likeness(F.col("sketch"), F.col("edited_sketch"), scale).alias("near_edited"),
        likeness(F.col("sketch"), F.col("next.sketch"), scale).alias("near_next"),
        F.size("sketch.hashes").alias("kept"),
    )

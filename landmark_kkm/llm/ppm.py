"""Prediction by partial matching over bytes: context trie, escapes, symbol exclusion; code lengths in log10.

The trie holds every context of up to ORDER bytes that the training texts have, and no task or driver holds it whole: a row for each
window (context and symbol), from the longest order down, each order summed from the next longer one in one shuffle. Along with the
trained windows go those that only held-out texts have, with a count of 0, so that each window that is ever asked for has a row, and
its code length follows from its own row and those of its suffixes. A scan cuts its texts into chunks of bounded size; a chunk asks for
its distinct windows and words, packed by buckets of their hashes, and the answers meet its texts. So what is counted grows with the
corpus, and what a task holds does not. `adaptive_log10` is the form that learns only from the text itself.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from math import log10

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from landmark_kkm.llm.texts import as_bytes, joined, mix, packed, release, slices, unpacked
from landmark_kkm.session import materialize, ship

ORDER = 5
#: Bytes that UTF-8 never has: before the text, and after it.
START, END = 0xFE, 0xFF
SYMBOLS = 256
#: Text bytes of a chunk, which one task scores, and of a bucket: the requests of all chunks for the windows of a bucket meet in one task.
CHUNK_BYTES, BUCKET_BYTES = 24 << 20, 16 << 20
LEAST_BUCKETS = 32
_SLICE = 1 << 20
TEXT, GRAM, WORD = -1, 0, 1


def held_out(id_col: str = "doc_id", folds: int = 10, held: int = 0):
    """crc32 of the id as text falls in the held fold; null ids are held out too."""
    return F.coalesce(F.crc32(F.encode(F.col(id_col).cast("string"), "UTF-8")) % folds == held, F.lit(True))


def _words(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row of each word, index of each word, 64-bit keys of the distinct words) of a slice."""
    lists = pc.ascii_split_whitespace(pc.ascii_lower(pc.fill_null(batch.column("text"), "")))
    rows, words = pc.list_parent_indices(lists), pc.list_flatten(lists)
    full = pc.greater(pc.binary_length(words), 0)
    coded = words.filter(full).dictionary_encode()
    keys = np.array([xxhash.xxh64_intdigest(w, 7) for w in coded.dictionary.cast(pa.binary()).to_pylist()], dtype=np.uint64).view(np.int64)
    return rows.filter(full).to_numpy(zero_copy_only=False).astype(np.int64), coded.indices.to_numpy(zero_copy_only=False), keys


def _keys_of(data: np.ndarray) -> np.ndarray:
    key = np.zeros(max(0, len(data) - ORDER), np.int64)
    for i in range(ORDER + 1):
        key = key << 8 | data[i : len(data) - ORDER + i]
    return key


def windows(texts: list[bytes]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(text, window) of every byte and end mark of the texts, in blocks: the ORDER + 1 bytes that end there, A-Z lower-cased, as one number."""
    pad, end = bytes([START]) * ORDER, bytes([END])
    block, size = [], 0
    for i, text in enumerate([*texts, None]):
        if block and (text is None or size + len(text) > _SLICE):
            data = np.frombuffer(b"".join(pad + texts[j].lower() + end for j in block), np.uint8)
            keys = _keys_of(data)[data[ORDER:] != START]
            yield np.repeat(block, [len(texts[j]) + 1 for j in block]), keys
            block, size = [], 0
        if text is None:
            return
        if len(text) > _SLICE:
            data = np.frombuffer(pad + text.lower() + end, np.uint8)
            for at in range(0, len(data) - ORDER, _SLICE):
                keys = _keys_of(data[at : at + ORDER + _SLICE])
                yield np.full(len(keys), i), keys
        else:
            block.append(i)
            size += len(text) + ORDER


class _Tally:
    """Counts by key; memory follows the distinct keys."""

    def __init__(self):
        self.parts, self.rows, self.least = [], 0, 400_000

    def add(self, keys: np.ndarray, counts: np.ndarray) -> None:
        code, found = pd.factorize(keys)
        self.parts.append((found, np.bincount(code, weights=counts, minlength=len(found)).astype(np.int64)))
        self.rows += len(found)
        if self.rows > self.least and len(self.parts) > 1:
            self.parts = [self.total()]
            self.rows = len(self.parts[0][0])
            self.least = 2 * self.rows + 400_000

    def total(self) -> tuple[np.ndarray, np.ndarray]:
        if not self.parts:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        code, found = pd.factorize(np.concatenate([p[0] for p in self.parts]))
        return found, np.bincount(code, weights=np.concatenate([p[1] for p in self.parts]), minlength=len(found)).astype(np.int64)


def _bucket_of(kind: int, keys: np.ndarray, buckets: int) -> np.ndarray:
    """Windows of one context share a bucket."""
    hashed = mix((keys >> 8).view(np.uint64), 3) if kind == GRAM else keys.view(np.uint64)
    return (hashed % np.uint64(buckets)).astype(np.int32)


REQUEST_DDL = "chunk long, kind int, bucket int, keys binary, counts binary"
_REQUEST = pa.schema([("chunk", pa.int64()), ("kind", pa.int32()), ("bucket", pa.int32()), ("keys", pa.binary()), ("counts", pa.binary())])


def _request_rows(batches: Iterator[pa.RecordBatch], buckets: int, chunk_bytes: int) -> Iterator[pa.RecordBatch]:
    """For each chunk: its texts, in compressed slices, and its distinct windows and words with their counts in training texts (0 for those that only held-out texts have)."""
    release()
    base, number = TaskContext.get().partitionId() << 24, 0
    tallies, size = (_Tally(), _Tally()), 0
    for whole in batches:
        for batch in slices(whole, "text", _SLICE):
            texts = as_bytes(batch.column("text"))
            train = batch.column("train").to_numpy(zero_copy_only=False).astype(np.int64)
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, batch.schema, options=pa.ipc.IpcWriteOptions(compression=pa.Codec("zstd", compression_level=1))) as writer:
                writer.write_batch(batch)
            yield pa.RecordBatch.from_pylist([{"chunk": base + number, "kind": TEXT, "bucket": TEXT, "keys": sink.getvalue().to_pybytes()}], schema=_REQUEST)
            for owner, keys in windows(texts):
                tallies[GRAM].add(keys, train[owner])
            rows, code, keys = _words(batch)
            tallies[WORD].add(keys[code], train[rows])
            size += sum(map(len, texts)) + 16 * len(texts)
            if size >= chunk_bytes:
                yield from _requests(tallies, base + number, buckets)
                tallies, size, number = (_Tally(), _Tally()), 0, number + 1
    yield from _requests(tallies, base + number, buckets)
    del tallies
    release()


def _requests(tallies: tuple[_Tally, _Tally], chunk: int, buckets: int) -> Iterator[pa.RecordBatch]:
    for kind, tally in zip((GRAM, WORD), tallies):
        keys, counts = tally.total()
        if not len(keys):
            continue
        order = np.argsort(keys)
        keys, counts = keys[order], counts[order]
        bucket = _bucket_of(kind, keys, buckets)
        order = np.argsort(bucket, kind="stable")
        names, first = np.unique(bucket[order], return_index=True)
        rows = [{"chunk": chunk, "kind": kind, "bucket": int(b), "keys": packed(keys[part], True), "counts": packed(counts[part])} for b, part in zip(names, np.split(order, first[1:]))]
        yield pa.RecordBatch.from_pylist(rows, schema=_REQUEST)


def _summed(table: pa.Table) -> pa.Table:
    """The counts of a bucket, over all chunks."""
    keys, counts = ([unpacked(x, rising=c == "keys") for x in table.column(c).to_pylist()] for c in ("keys", "counts"))
    code, keys = pd.factorize(joined(keys))
    counts = np.bincount(code, weights=joined(counts), minlength=len(keys)).astype(np.int64)
    kind, bucket = (np.full(len(keys), table.column(c)[0].as_py(), np.int32) for c in ("kind", "bucket"))
    return pa.table({"kind": kind, "bucket": bucket, "key": keys, "n": counts})


def _answered(asked: pa.Table, known: pa.Table) -> pa.Table:
    """The values of the keys that each chunk asked for, in its order: code lengths in single precision, counts of words in double."""
    if not asked.num_rows:
        return pa.table({"chunk": pa.array([], pa.int64()), "kind": pa.array([], pa.int32()), "keys": pa.array([], pa.binary()), "answers": pa.array([], pa.binary())})
    index = pd.Index(known.column("key").to_numpy())
    values = known.column("value").to_numpy().astype(ANSWER[asked.column("kind")[0].as_py()])
    out = [packed(values[index.get_indexer(unpacked(keys, rising=True))]) for keys in asked.column("keys").to_pylist()]
    return pa.table({"chunk": asked.column("chunk"), "kind": asked.column("kind"), "keys": asked.column("keys"), "answers": pa.array(out, pa.binary())})


ANSWER = {GRAM: np.float32, WORD: np.float64}


def code_lengths(grams: DataFrame) -> DataFrame:
    """grams (key, n), each window once, n its count in training, with value: log10 of the probability of its symbol after its context.

    A context gives half a count of each of its symbols to the escape; symbols of longer contexts are excluded in shorter ones. All symbols of a
    context are in its suffix too, so what is left there is the suffix's total less the counts, there, of the context's symbols. Where the trie has
    none, the 256 less the symbols known are alike. A context never seen in training passes to its suffix at no cost."""
    top, missed, level = None, [], grams
    for k in range(ORDER, 0, -1):
        rows = level.select("key", "n", F.shiftright("key", 8).alias("node"), F.col("key").bitwiseAND(F.lit((1 << 8 * k) - 1)).alias("sub"))
        seen = F.when(F.col("n") > 0, 1)
        if k > 1:
            rows = rows.withColumn("up", F.shiftright("sub", 8)).repartition("up")
            suffix, context, entry = (Window.partitionBy(*c) for c in (("up",), ("up", "node"), ("up", "sub")))
            rows = rows.withColumn("short", F.sum("n").over(entry))
            rows = rows.withColumn("up_all", F.sum("n").over(suffix)).withColumn("up_kinds", F.size(F.collect_set(F.when(F.col("n") > 0, F.col("sub"))).over(suffix)))
        else:  # the root: 256 symbols at most
            root = rows.groupBy(F.col("sub").alias("root_sub")).agg(F.sum("n").alias("short"))
            found = root.agg(F.sum("short"), F.sum((F.col("short") > 0).cast("long"))).first()
            unseen = -log10(SYMBOLS - (found[1] or 0))
            context = Window.partitionBy("node")
            rows = rows.join(F.broadcast(root), F.col("sub") == F.col("root_sub")).withColumn("up_all", F.lit(found[0] or 0)).withColumn("up_kinds", F.lit(found[1] or 0))
        rows = rows.withColumn("all", F.sum("n").over(context)).withColumn("kinds", F.coalesce(F.sum(seen).over(context), F.lit(0)))
        rows = rows.withColumn("taken", F.coalesce(F.sum(F.when(F.col("n") > 0, F.col("short"))).over(context), F.lit(0)))
        left = F.col("up_all") - F.col("taken")
        escape = F.log10((F.col("up_kinds") - F.col("kinds")) / (2 * left))
        part = F.when(left <= 0, F.lit(0.0)).when(F.col("short") > 0, F.log10((2 * F.col("short") - 1) / (2 * left))).otherwise(escape)
        own = F.when(F.col("n") > 0, F.log10((2 * F.col("n") - 1) / (2 * F.col("all")))).otherwise(F.when(F.col("all") > 0, F.log10(F.col("kinds") / (2 * F.col("all")))).otherwise(F.lit(0.0)))
        rows = rows.select("key", "sub", "n", F.when(F.col("n") == 0, part).alias("part"), (F.col("short") == 0).alias("more"), *([own.alias("own")] if k == ORDER else []))
        rows = materialize(rows, "order")
        top = rows if top is None else top
        missed.append(rows.filter("n = 0").select("key", "sub", "part", "more"))
        level = rows.groupBy(F.col("sub").alias("key")).agg(F.sum("n").alias("n"))
    below = missed.pop().select("key", (F.col("part") + F.when(F.col("more"), F.lit(unseen)).otherwise(F.lit(0.0))).alias("below"))
    while missed:
        rows = missed.pop().join(below.withColumnRenamed("key", "sub"), "sub", "left")
        below = rows.select("key", (F.col("part") + F.when(F.col("more"), F.col("below")).otherwise(F.lit(0.0))).alias("below"))
    known = top.filter("n > 0").select("key", F.col("own").alias("value"))
    return known.unionByName(top.filter("n = 0").join(below, "key").select("key", (F.col("own") + F.col("below")).alias("value")))


SCORE_DDL = "doc_id long, n_tokens long, n_known long, base_score double, score double"


_SCORED = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("base_score", pa.float64()), ("score", pa.float64())])


def _score_rows(texts: pa.Table, answers: pa.Table, ends: int, below: float) -> pa.Table:
    """The texts of a chunk, by the answers to it."""
    release()
    kinds, keys, values = (answers.column(c).to_pylist() for c in ("kind", "keys", "answers"))
    index, value = {}, {}
    for kind in (GRAM, WORD):
        mine = [i for i, k in enumerate(kinds) if k == kind]
        index[kind] = pd.Index(joined([unpacked(keys[i], rising=True) for i in mine]))
        value[kind] = joined([unpacked(values[i], ANSWER[kind]) for i in mine], float).astype(float)
    out = []
    for blob in texts.column("keys").to_pylist():
        for batch in pa.ipc.open_stream(blob):
            n = batch.num_rows
            score = np.zeros(n)
            for owner, found in windows(as_bytes(batch.column("text"))):
                score += np.bincount(owner, weights=value[GRAM][index[GRAM].get_indexer(found)], minlength=n)
            rows, code, words = _words(batch)
            found = value[WORD][index[WORD].get_indexer(words)] if len(words) else np.zeros(0)
            base = np.bincount(rows, weights=(np.log10(found + 0.1) - below)[code], minlength=n) + log10(ends + 0.1) - below
            n_known = np.bincount(rows, weights=(found > 0)[code], minlength=n).astype(np.int64) + (ends > 0)
            n_tokens = np.bincount(rows, minlength=n).astype(np.int64) + 1
            out.append(pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n_tokens), pa.array(n_known), pa.array(base), pa.array(score)], schema=_SCORED))
    return pa.Table.from_batches(out, _SCORED)


def score_documents(docs: DataFrame, chunk_bytes: int = CHUNK_BYTES, bucket_bytes: int = BUCKET_BYTES) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score) of every document.

    The model and the word counts come from all rows whose crc32(doc_id as text) mod 10 is not 0; rows with a null doc_id are held out. base_score
    is the smoothed unigram log10 probability of the tokens (words and one end), score the byte model's log10 probability of the whole text, A-Z
    lower-cased, white space and all, with an end mark. Null and empty texts have one token. Repeated rows each come back. An empty table gives no
    rows; without training rows score is that of uniform bytes. Words are counted by 64-bit keys. Other columns are ignored.

    Sizes decide on the number of chunks and buckets alone, not on results."""
    spark = docs.sparkSession
    ship(spark)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    size, ends = rows.agg(F.sum(F.octet_length("text")), F.sum((~held_out()).cast("long"))).first()
    size, ends = size or 0, ends or 0
    buckets = max(LEAST_BUCKETS, -(-size // bucket_bytes))
    asked = rows.withColumn("train", ~held_out()).mapInArrow(lambda it: _request_rows(it, buckets, chunk_bytes), REQUEST_DDL)
    asked = materialize(asked, "asked")
    requests = asked.filter(F.col("kind") != TEXT)
    counts = materialize(requests.groupBy("kind", "bucket").applyInArrow(_summed, "kind int, bucket int, key long, n long"), "counts")
    words = counts.filter(F.col("kind") == WORD)
    total, kinds = words.agg(F.sum("n"), F.sum((F.col("n") > 0).cast("long"))).first()
    total, kinds = (total or 0) + ends, (kinds or 0) + (ends > 0)
    below = float(np.log10(total + 0.1 * (kinds + 1)))
    grams = counts.filter(F.col("kind") == GRAM)
    values = code_lengths(grams.select("key", "n")).join(grams.select("key", "bucket"), "key").select(F.lit(GRAM).alias("kind"), "bucket", "key", "value")
    values = values.unionByName(words.select("kind", "bucket", "key", F.col("n").cast("double").alias("value")))
    answers = requests.select("chunk", "kind", "bucket", "keys").groupBy("kind", "bucket").cogroup(values.groupBy("kind", "bucket"))
    answers = answers.applyInArrow(_answered, "chunk long, kind int, keys binary, answers binary")
    texts = asked.filter(F.col("kind") == TEXT).select("chunk", "keys")
    chunks = 4 * max(spark.sparkContext.defaultParallelism, -(-size // chunk_bytes))  # more tasks than chunks, so that few hold more than one
    scored = texts.repartition(chunks, "chunk").groupBy("chunk").cogroup(answers.repartition(chunks, "chunk").groupBy("chunk")).applyInArrow(lambda t, a: _score_rows(t, a, ends, below), "doc_id long, n_tokens long, n_known long, base_score double, score double")
    return scored.select("doc_id", held_out().alias("held_out"), "n_tokens", "n_known", F.lit(total).cast("long").alias("train_tokens"), "base_score", "score")


def adaptive_log10(text: bytes, order: int = ORDER) -> float:
    """log10 probability of a text (and its end) under a model that starts empty and learns each symbol after coding it."""
    tries: list[defaultdict] = [defaultdict(lambda: defaultdict(int)) for _ in range(order + 1)]
    data, total = bytes([START]) * order + text + bytes([END]), 0.0
    for i in range(order, len(data)):
        excluded: set[int] = set()
        p, found = 1.0, False
        for k in range(order, -1, -1):
            seen = {s: n for s, n in tries[k][data[i - k : i]].items() if s not in excluded}
            if seen and not found:
                mass = 2 * sum(seen.values())
                if data[i] in seen:
                    p, found = p * (2 * seen[data[i]] - 1) / mass, True
                else:
                    p *= len(seen) / mass
                    excluded |= set(seen)
        total += log10(p if found else p / (SYMBOLS - len(excluded)))
        for k in range(order + 1):
            tries[k][data[i - k : i]][data[i]] += 1
    return total

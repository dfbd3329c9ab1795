"""Line dedup with two Bloom filters: only lines that the corpus may hold twice are shuffled and counted exactly.

The filters are cut by ranges of the line hash. A scan sends the hashes of its distinct lines, a few bytes each, to the ranges; the task
of a range adds them to its `once` and `twice` filters and names those that `twice` has. So the filters grow with the corpus, no task or
driver holds all of them, and the share of lines that is suspected without cause does not depend on the size of the corpus.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from landmark_kkm.llm.texts import as_bytes, packed, release, slices, unpacked
from landmark_kkm.session import materialize, ship

MIN_CHARS = 40
MIN_DOCS = 5
#: Filter bits for each hash that a range gets, and probes for each: about one line in 400 is suspected without cause.
BITS_PER_HASH, PROBES = 16, 4
#: Text bytes whose lines a scan sends at a time, and whose lines a range gets.
CHUNK_BYTES, RANGE_BYTES = 64 << 20, 64 << 20
LEAST_RANGES = 32
#: Bytes of suspected hashes, or of confirmed keys, up to which they are broadcast; beyond that lines, or documents, meet them by a shuffle.
BROADCAST_BYTES = 64 << 20


def key_of(line: bytes, least: int = MIN_CHARS) -> bytes | None:
    """The line stripped of ASCII white space and lower-cased (A-Z), or None under `least` code points."""
    key = line.strip().lower()
    if len(key) < least or not key.isascii() and len(key.decode("utf-8", "replace")) < least:
        return None
    return key


def probes(hashes: np.ndarray, bits: int) -> np.ndarray:
    """PROBES bit positions for each hash, as rows."""
    low, high = hashes & np.uint64(0xFFFFFFFF), hashes >> np.uint64(32) | np.uint64(1)
    return np.stack([(low + np.uint64(i) * high) & np.uint64(bits - 1) for i in range(PROBES)]).astype(np.int64)


class TwoFilters:
    """`once` holds every hash; `twice` each that was added again, and by chance a few more, but never too few."""

    def __init__(self, bits: int):
        self.bits = bits
        self.once, self.twice = np.zeros(bits // 8, np.uint8), np.zeros(bits // 8, np.uint8)

    @staticmethod
    def _set(to: np.ndarray, at: np.ndarray) -> None:
        np.bitwise_or.at(to, at.ravel() >> 3, (1 << (at.ravel() & 7)).astype(np.uint8))

    @staticmethod
    def has(held: np.ndarray, at: np.ndarray) -> np.ndarray:
        return (held[at >> 3] >> (at & 7).astype(np.uint8) & 1).all(0)

    def add(self, hashes: np.ndarray) -> None:
        hashes, count = np.unique(hashes, return_counts=True)
        at = probes(hashes, self.bits)
        again = self.has(self.once, at) | (count > 1)
        self._set(self.twice, at[:, again])
        self._set(self.once, at)


def _keys(texts: list[bytes], least: int) -> Iterator[tuple[int, bytes]]:
    """(row, key) of each text's distinct keys."""
    for row, text in enumerate(texts):
        seen = set()
        for line in text.split(b"\n"):
            if len(line) >= least and (key := key_of(line, least)) is not None and key not in seen:
                seen.add(key)
                yield row, key


def _hash(keys: list[bytes]) -> np.ndarray:
    return np.array([xxhash.xxh64_intdigest(k) for k in keys], dtype=np.uint64)


_RANGES = pa.schema([("part", pa.int32()), ("hashes", pa.binary())])


def _range_rows(batches: Iterator[pa.RecordBatch], ranges: int, least: int, chunk_bytes: int) -> Iterator[pa.RecordBatch]:
    """The line hashes of a chunk, once for each document that has the line, by ranges."""
    release()
    held, size = [], 0

    def sent() -> Iterator[pa.RecordBatch]:
        hashes = np.sort(np.concatenate(held))
        part = ((hashes >> np.uint64(32)) * np.uint64(ranges) >> np.uint64(32)).astype(np.int64)
        names, first = np.unique(part, return_index=True)
        yield pa.RecordBatch.from_pylist([{"part": int(n), "hashes": packed(x.view(np.int64), True)} for n, x in zip(names, np.split(hashes, first[1:]))], schema=_RANGES)

    for whole in batches:
        for batch in slices(whole, "text"):
            texts = as_bytes(batch.column("text"))
            held.append(_hash([k for _, k in _keys(texts, least)]))
            size += sum(map(len, texts))
            if size >= chunk_bytes:
                yield from sent()
                held, size = [], 0
    if held:
        yield from sent()


def _suspected(table: pa.Table) -> pa.Table:
    """The hashes of a range that its filters may have twice."""
    parts = [unpacked(x, rising=True).view(np.uint64) for x in table.column("hashes").to_pylist()]
    count = sum(map(len, parts))
    both = TwoFilters(1 << max(10, (BITS_PER_HASH * count - 1).bit_length()))
    for hashes in parts:
        both.add(hashes)
    again = [hashes[both.has(both.twice, probes(hashes, both.bits))] for hashes in map(np.unique, parts)]
    return pa.table({"hash": np.unique(np.concatenate(again)).view(np.int64)})


def suspected(docs: DataFrame, least: int = MIN_CHARS, chunk_bytes: int = CHUNK_BYTES, range_bytes: int = RANGE_BYTES) -> DataFrame:
    """(hash): of every line key that two documents or more have, and of a small share of the others."""
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    ranges = max(LEAST_RANGES, -(-size // range_bytes))
    sent = docs.select("text").mapInArrow(lambda it: _range_rows(it, ranges, least, chunk_bytes), "part int, hashes binary")
    return materialize(sent.groupBy("part").applyInArrow(_suspected, "hash long"), "suspected")


def _line_rows(batches: Iterator[pa.RecordBatch], held, least: int) -> Iterator[pa.RecordBatch]:
    """(doc_id, print, key) of the lines whose hashes are among those held."""
    for whole in batches:
        for batch in slices(whole, "text"):
            found = list(_keys(as_bytes(batch.column("text")), least))
            hashes = _hash([k for _, k in found]).view(np.int64)
            at = np.searchsorted(held.value, hashes)
            near = at < len(held.value)
            near[near] = held.value[at[near]] == hashes[near]
            found = [found[i] for i in np.flatnonzero(near)]
            rows = pa.array([r for r, _ in found], pa.int64())
            keys = pa.array([k for _, k in found], pa.binary()).cast(pa.string())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").take(rows), batch.column("print").take(rows), keys], names=["doc_id", "print", "key"])


def _hash_rows(batches: Iterator[pa.RecordBatch], least: int) -> Iterator[pa.RecordBatch]:
    """(doc_id, print, hash, at) of every line: at is its place among the keys of its text."""
    for whole in batches:
        for batch in slices(whole, "text"):
            found = list(_keys(as_bytes(batch.column("text")), least))
            rows = np.array([r for r, _ in found], np.int64)
            at = np.arange(len(rows)) - np.searchsorted(rows, rows)
            take = pa.array(rows)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").take(take), batch.column("print").take(take), pa.array(_hash([k for _, k in found]).view(np.int64)), pa.array(at)], names=["doc_id", "print", "hash", "at"])


def _asked_lines(batches: Iterator[pa.RecordBatch], least: int) -> Iterator[pa.RecordBatch]:
    """(doc_id, print, key) of the lines at the places that a row asks for."""
    for whole in batches:
        for batch in slices(whole, "text"):
            keys: dict[int, list[bytes]] = {}
            for row, key in _keys(as_bytes(batch.column("text")), least):
                keys.setdefault(row, []).append(key)
            asked = batch.column("places").to_pylist()
            found = [(row, keys[row][i]) for row in sorted(keys) for i in asked[row]]
            rows = pa.array([r for r, _ in found], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").take(rows), batch.column("print").take(rows), pa.array([k for _, k in found], pa.binary()).cast(pa.string())], names=["doc_id", "print", "key"])


def _suspect_lines(slim: DataFrame, hashes: DataFrame, least: int, min_docs: int, broadcast_bytes: int) -> DataFrame:
    """(doc_id, print, key) of the suspected lines. Where their hashes are too many to broadcast, the hashes of all lines meet them by a
    shuffle, and of those that enough documents have the documents' texts give the lines."""
    ddl = "doc_id long, print long, key string"
    if 8 * hashes.count() <= broadcast_bytes:
        held = slim.sparkSession.sparkContext.broadcast(np.sort(hashes.toPandas()["hash"].to_numpy(np.int64)))
        return slim.mapInArrow(lambda it: _line_rows(it, held, least), ddl)
    lines = slim.mapInArrow(lambda it: _hash_rows(it, least), "doc_id long, print long, hash long, at long").join(hashes, "hash", "left_semi")
    lines = materialize(lines, "hashes")
    often = lines.select("hash", "doc_id").distinct().groupBy("hash").agg(F.count("doc_id").alias("n")).filter(F.col("n") >= min_docs).select("hash")
    places = lines.join(often, "hash", "left_semi").groupBy("doc_id", "print").agg(F.collect_set("at").alias("places"))
    asked = slim.join(places.select(F.col("doc_id").alias("d"), F.col("print").alias("p"), "places"), F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("print") == F.col("p")))
    return asked.select("doc_id", "print", "text", "places").mapInArrow(lambda it: _asked_lines(it, least), ddl)


def _rewrite(batches: Iterator[pa.RecordBatch], drops_of, least: int, text_at: int) -> Iterator[pa.RecordBatch]:
    """Columns: doc_id, the row's own keys or null, then the caller's by position; drops_of(batch, row) is a function of a key that tells whether the row loses its lines."""
    for whole in batches:
        named = pa.RecordBatch.from_arrays(whole.columns, names=[str(i) for i in range(whole.num_columns)])
        for batch in slices(named, str(text_at)):
            texts, counts, gone = [], [], []
            for row, text in enumerate(as_bytes(batch.column(text_at))):
                lines, goes = text.split(b"\n"), drops_of(batch, row)
                kept = [x for x in lines if len(x) < least or (k := key_of(x, least)) is None or not goes(k)]
                texts.append(text if len(kept) == len(lines) else b"\n".join(kept))
                counts.append(len(lines))
                gone.append(len(lines) - len(kept))
            columns = list(batch.columns)
            columns[text_at] = pa.array(texts, pa.binary()).cast(pa.string())
            columns = [pa.array(counts, pa.int64()), pa.array(gone, pa.int64()), *columns[2:]]
            yield pa.RecordBatch.from_arrays(columns, names=[f"c{i}" for i in range(len(columns))])


def _by_table(table) -> callable:
    def of(batch, row):
        doc, held = batch.column(0)[row].as_py(), table.value
        return lambda key: key in held and (doc is None or held[key] != doc)

    return of


def _by_column(batch, row):
    own = set(x.encode() for x in batch.column(1)[row].as_py() or ())
    return lambda key: key in own


def rewritten(docs: DataFrame, min_chars: int = MIN_CHARS, min_docs: int = MIN_DOCS, broadcast_bytes: int = BROADCAST_BYTES, **sizes: int) -> DataFrame:
    """The lines before (c0), those dropped (c1), and then the columns of docs as c2, c3, ..., its text without repeated lines."""
    ship(docs.sparkSession)
    spark = docs.sparkSession
    own = docs.toDF(*[f"c{i + 2}" for i in range(len(docs.columns))])
    id_at, text_at = (docs.columns.index(c) + 2 for c in ("doc_id", "text"))
    own = own.withColumn(f"c{text_at}", F.col(f"c{text_at}").cast("string")).withColumn("d", F.col(f"c{id_at}").cast("long"))
    slim = own.select(F.col("d").alias("doc_id"), F.col(f"c{text_at}").alias("text"), F.xxhash64(f"c{text_at}").alias("print"))
    suspects = _suspect_lines(slim, suspected(slim, min_chars, **sizes), min_chars, min_docs, broadcast_bytes)
    each = suspects.filter("doc_id is not null").select("key", "doc_id").distinct()
    repeated = materialize(each.groupBy("key").agg(F.count("*").alias("n"), F.max("doc_id").alias("keeper")).filter(F.col("n") >= min_docs).drop("n"), "lines")
    size = repeated.agg(F.sum(F.octet_length("key") + 64)).first()[0] or 0
    kept = [F.col(f.name) for f in own.schema.fields if f.name != "d"]
    out = T.StructType([T.StructField("c0", T.LongType()), T.StructField("c1", T.LongType()), *[f for f in own.schema.fields if f.name != "d"]])
    if size <= broadcast_bytes:
        table = spark.sparkContext.broadcast({k.encode(): d for k, d in repeated.collect()})
        met = own.select("d", F.lit(None).cast("array<string>").alias("own"), *kept)
        return met.mapInArrow(lambda it: _rewrite(it, _by_table(table), min_chars, text_at), out)
    lost = suspects.join(repeated, "key").filter(~F.col("doc_id").eqNullSafe(F.col("keeper")))
    lost = lost.groupBy("doc_id", "print").agg(F.collect_set("key").alias("own")).select(F.col("doc_id").alias("_d"), F.col("print").alias("_p"), "own")
    met = own.join(lost, F.col("d").eqNullSafe(F.col("_d")) & (F.xxhash64(f"c{text_at}") == F.col("_p")), "left").select("d", "own", *kept)
    return met.mapInArrow(lambda it: _rewrite(it, _by_column, min_chars, text_at), out)


def drop_repeated_lines(docs: DataFrame, min_chars: int = MIN_CHARS, min_docs: int = MIN_DOCS, broadcast_bytes: int = BROADCAST_BYTES, **sizes: int) -> DataFrame:
    """All rows and columns of docs, `text` without repeated lines.

    A line's key is the line stripped of ASCII white space with A-Z lower-cased. Keys of min_chars code points or more that min_docs documents
    (distinct doc_ids) or more hold lose all their lines but those in rows with the largest doc_id among them. Null text counts as one empty line and
    comes back empty. A row with a null doc_id is no document that is counted or keeps; it loses repeated lines like any other. Rows that repeat a
    doc_id count once, and keep or lose alike. An empty table gives none. Other columns may have any names. What the filters suspect is counted exactly."""
    found = rewritten(docs, min_chars, min_docs, broadcast_bytes, **sizes)
    return found.select(*[F.col(f"c{i + 2}").alias(c) for i, c in enumerate(docs.columns)])


def with_length(docs: DataFrame) -> DataFrame:
    """docs with n_chars, where it has that column, set to the code points of its text."""
    if "n_chars" not in docs.columns:
        return docs
    kind = docs.schema["n_chars"].dataType
    return docs.withColumn("n_chars", F.char_length("text").cast(kind)).select(docs.columns)


def line_report(docs: DataFrame) -> DataFrame:
    """(doc_id, n_lines, n_dropped, kept_sha256) of every document."""
    kept = rewritten(docs.select("doc_id", "text"))
    return kept.select(F.col("c2").alias("doc_id"), F.col("c0").alias("n_lines"), F.col("c1").alias("n_dropped"), F.sha2(F.encode("c3", "UTF-8"), 256).alias("kept_sha256"))


#: The same rule in SQL.
LINE_SQL = r"""
WITH split AS (
  SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS ls FROM documents
), numbered AS (
  SELECT doc_id, unnest(ls) AS line, unnest(range(1, len(ls) + 1)) AS i FROM split
), keyed AS (
  SELECT doc_id, i, line,
         translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k
  FROM numbered
), repeated AS (
  SELECT k, max(doc_id) AS keeper FROM keyed WHERE length(k) >= 40 GROUP BY k HAVING count(DISTINCT doc_id) >= 5
), marked AS (
  SELECT doc_id, i, line, (r.k IS NOT NULL AND r.keeper <> doc_id) AS gone FROM keyed LEFT JOIN repeated r ON keyed.k = r.k
)
SELECT doc_id, CAST(count(*) AS BIGINT) AS n_lines, CAST(count(*) FILTER (gone) AS BIGINT) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (NOT gone), '')) AS kept_sha256
FROM marked GROUP BY doc_id
"""

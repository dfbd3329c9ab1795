"""Language ID: sparse multinomial logistic regression on TF-IDF character n-grams, trained by follow-the-regularised-leader
with elastic-net penalties, calibrated by a temperature."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from landmark_kkm.llm.texts import slices
from landmark_kkm.session import ship

GRAMS = (1, 2, 3)
BUCKET_BITS = 15
BUCKETS = 1 << BUCKET_BITS
#: Labelled rows of each language that the weights are fitted on, chosen by a hash of the id; document frequencies come from all training rows.
FIT_ROWS = 1000
EPOCHS = 4
#: Frequencies are scaled so that an n-gram of a typical text weighs about 1.
SCALE = 64.0
UNKNOWN = "und"
_CHARS = 1 << 21


def code_points(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Lower-cased code points of all the texts, each followed by a 0, and where each begins (with the end last)."""
    parts = [np.frombuffer((t + "\0").encode("utf-32-le", "replace"), np.uint32) for t in pc.utf8_lower(pc.fill_null(texts, "")).to_pylist()]
    starts = np.cumsum([0, *map(len, parts)])
    return (np.concatenate(parts) if parts else np.zeros(0, np.uint32)), starts


def buckets(points: np.ndarray, n: int) -> np.ndarray:
    """The bucket of the n-gram at each position; -1 where it would run over the text's end."""
    out = np.full(len(points), -1, np.int32)
    m = len(points) - n + 1
    if m <= 0:
        return out
    ends = points == 0
    key, over = np.full(m, n, np.uint32), np.zeros(m, bool)
    for i in range(n):
        key = (key * np.uint32(0x01000193)) ^ points[i : i + m]
        over |= ends[i : i + m]
    key = (key ^ key >> np.uint32(15)) * np.uint32(0x2C1B3C6D)
    out[:m] = np.where(over, -1, (key >> np.uint32(32 - BUCKET_BITS)).astype(np.int32))
    return out


def counts(points: np.ndarray) -> np.ndarray:
    """How often each bucket occurs in one text."""
    found = np.zeros(BUCKETS, np.int64)
    for n in GRAMS:
        b = buckets(points, n)
        found += np.bincount(b[b >= 0], minlength=BUCKETS)
    return found


@dataclass
class Model:
    langs: list[str]
    weights: np.ndarray  # (BUCKETS + 1, langs), the inverse document frequency and the scale worked in; the last row is 0
    bias: np.ndarray
    temperature: float = 1.0

    def logits(self, points: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """A row for each text: bias + mean over its n-grams."""
        total, length = np.zeros((len(starts) - 1, len(self.langs))), np.zeros(len(starts) - 1)
        for n in GRAMS:
            b = buckets(points, n)
            total += np.add.reduceat(self.weights[b], starts[:-1], axis=0, dtype=np.float64)
            length += np.add.reduceat((b >= 0).astype(np.int64), starts[:-1])
        return self.bias + total / np.maximum(length, 1)[:, None]

    def probabilities(self, logits: np.ndarray) -> np.ndarray:
        z = logits / self.temperature
        z = np.exp(z - z.max(1, keepdims=True))
        return z / z.sum(1, keepdims=True)


class Ftrl:
    """Per-coordinate follow-the-regularised-leader for a softmax, with l1 and l2 penalties. The bias has no penalty."""

    def __init__(self, features: int, classes: int, alpha: float = 0.5, beta: float = 1.0, l1: float = 0.02, l2: float = 0.02):
        self.z, self.n = np.zeros((features, classes)), np.zeros((features, classes))
        self.bias_z, self.bias_n = np.zeros(classes), np.zeros(classes)
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2

    def weights(self, at=slice(None)) -> np.ndarray:
        z, n = self.z[at], self.n[at]
        return np.where(np.abs(z) <= self.l1, 0.0, -(z - np.sign(z) * self.l1) / ((self.beta + np.sqrt(n)) / self.alpha + self.l2))

    def bias(self) -> np.ndarray:
        return -self.bias_z / ((self.beta + np.sqrt(self.bias_n)) / self.alpha)

    def update(self, at: np.ndarray, x: np.ndarray, y: int) -> None:
        w, b = self.weights(at), self.bias()
        p = x @ w + b
        p = np.exp(p - p.max())
        p /= p.sum()
        p[y] -= 1
        g = x[:, None] * p
        root = np.sqrt(self.n[at] + g * g)
        self.z[at] += g - (root - np.sqrt(self.n[at])) / self.alpha * w
        self.n[at] += g * g
        grown = np.sqrt(self.bias_n + p * p)
        self.bias_z += p - (grown - np.sqrt(self.bias_n)) / self.alpha * b
        self.bias_n += p * p


def temperature_of(logits: np.ndarray, y: np.ndarray) -> float:
    """The temperature that makes held-back rows likeliest, by golden section on its logarithm."""

    def loss(t: float) -> float:
        z = logits / np.exp(t)
        z -= z.max(1, keepdims=True)
        return float((np.log(np.exp(z).sum(1)) - z[np.arange(len(y)), y]).mean())

    low, high, ratio = -3.0, 4.0, (5**0.5 - 1) / 2
    for _ in range(40):
        a, b = high - ratio * (high - low), low + ratio * (high - low)
        low, high = (low, b) if loss(a) < loss(b) else (a, high)
    return float(np.exp((low + high) / 2))


def _frequency_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Document frequency of each bucket in the partition, and its rows under -1."""
    found, rows = np.zeros(BUCKETS, np.int64), 0
    for whole in batches:
        for batch in slices(whole, "text", _CHARS):
            points, starts = code_points(batch.column("text"))
            for a, b in zip(starts, starts[1:]):
                found += counts(points[a:b]) > 0
            rows += batch.num_rows
    at = np.flatnonzero(found)
    yield pa.RecordBatch.from_arrays([pa.array(np.append(at, -1).astype(np.int32)), pa.array(np.append(found[at], rows))], names=["bucket", "n"])


def _vector_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for batch in slices(whole, "text", _CHARS):
            points, starts = code_points(batch.column("text"))
            held = [counts(points[a:b]) for a, b in zip(starts, starts[1:])]
            at = [np.flatnonzero(c).astype(np.int32) for c in held]
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), batch.column("lang"), pa.array([a.tobytes() for a in at], pa.binary()), pa.array([c[a].astype(np.int32).tobytes() for c, a in zip(held, at)], pa.binary())],
                names=["doc_id", "lang", "at", "times"],
            )


def fit(vectors: pd.DataFrame, frequency: np.ndarray, n_docs: int, epochs: int = EPOCHS) -> Model:
    """A model from (doc_id, lang, at, times), one row in five kept back for the temperature."""
    langs = sorted(vectors["lang"].unique())
    idf = np.log((1 + n_docs) / (1 + frequency)) + 0.1
    rows = []
    for doc, lang, at, times in vectors[["doc_id", "lang", "at", "times"]].sort_values("doc_id").itertuples(index=False):
        at, times = np.frombuffer(at, np.int32), np.frombuffer(times, np.int32)
        rows.append((at, SCALE * idf[at] * times / max(1, times.sum()), langs.index(lang)))
    order = np.random.default_rng(0).permutation(len(rows))
    back = set(order[: len(rows) // 5].tolist())
    learner = Ftrl(BUCKETS, len(langs))
    for epoch in range(epochs):
        for i in np.random.default_rng(epoch).permutation(len(rows)):
            if i not in back:
                learner.update(*rows[i])
    w, bias = learner.weights(), learner.bias()
    weights = np.zeros((BUCKETS + 1, len(langs)), np.float32)
    weights[:-1] = SCALE * idf[:, None] * w
    model = Model(langs, weights, bias)
    if back:
        logits = np.array([rows[i][1] @ w[rows[i][0]] + bias for i in sorted(back)])
        model.temperature = temperature_of(logits, np.array([rows[i][2] for i in sorted(back)]))
    return model


def _learnable():
    return F.coalesce(F.crc32(F.encode(F.col("doc_id").cast("string"), "UTF-8")) % 3 != 1, F.lit(False))


def learn(docs: DataFrame, rows: int = FIT_ROWS) -> Model | None:
    """A model from the rows with text, lang and doc_id whose crc32(doc_id as text) mod 3 is not 1; None if there are none."""
    ship(docs.sparkSession)
    known = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang")).filter(_learnable()).filter("text is not null and lang is not null")
    sizes = {r["lang"]: r["count"] for r in known.groupBy("lang").count().collect()}
    if not sizes:
        return None
    found = known.select("text").mapInArrow(_frequency_rows, "bucket int, n long").groupBy("bucket").agg(F.sum("n").alias("n")).toPandas()
    frequency, n_docs = np.zeros(BUCKETS), int(found.loc[found["bucket"] < 0, "n"].sum())
    found = found[found["bucket"] >= 0]
    frequency[found["bucket"]] = found["n"]
    share = F.coalesce(*[F.when(F.col("lang") == k, F.lit(min(1.0, rows / n))) for k, n in sizes.items()])
    picked = known.filter(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < share * (1 << 30))
    return fit(picked.mapInArrow(_vector_rows, "doc_id long, lang string, at binary, times binary").toPandas(), frequency, n_docs)


def _predict_rows(batches: Iterator[pa.RecordBatch], held) -> Iterator[pa.RecordBatch]:
    model: Model = held.value
    langs = np.array(model.langs, dtype=object)
    for whole in batches:
        for batch in slices(whole, "text", _CHARS):
            texts = batch.column("text")
            p = model.probabilities(model.logits(*code_points(texts)))
            letters = pc.fill_null(pc.match_substring_regex(texts, r"\p{L}"), False).to_numpy(zero_copy_only=False)
            best = p.argmax(1)
            lang, score = np.where(letters, langs[best], UNKNOWN), np.where(letters, p[np.arange(len(p)), best], 0.0)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(lang, pa.string()), pa.array(score)], names=["doc_id", "held_out", "lang_pred", "score"])


def predict(docs: DataFrame, model: Model | None) -> DataFrame:
    """(doc_id, held_out, lang_pred, score) of every document, score the calibrated probability of lang_pred.

    Null texts and texts without a letter are `und` with a score of 0, and so is everything without a model. Ties go to the first language by name.
    A null doc_id counts as held out. Repeated rows each come back."""
    ship(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (~_learnable()).alias("held_out"), F.col("text").cast("string").alias("text"))
    if model is None:
        return rows.select("doc_id", "held_out", F.lit(UNKNOWN).alias("lang_pred"), F.lit(0.0).alias("score"))
    held = docs.sparkSession.sparkContext.broadcast(model)
    return rows.mapInArrow(lambda it: _predict_rows(it, held), "doc_id long, held_out boolean, lang_pred string, score double")

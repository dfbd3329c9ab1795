"""Toxicity by a weighted lexicon, matched by Aho-Corasick on folded text, normalised by length, with exception phrases.

Folding gives each character its skeleton (homoglyphs, digit and sign substitutions), so that spellings that look alike match.
The lexicon is a short list of seeds and what the labelled rows teach: words and word beginnings that toxic rows hold and others
do not. Matches inside an exception phrase do not count. A logistic curve over the weight and its share of the words gives the score.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from landmark_kkm.llm.texts import slices
from landmark_kkm.session import ship, spread

# Seed words, exception phrases, homoglyphs and substitutions.
SEEDS = "asshole bastard bitch bullshit clown crap cretin disgusting dumbass fuck fucking garbage idiot idiots imbecile jerk loser losers moron morons pathetic retard scum scumbag shit shithead slut stupid trash trashy vermin whore worthless".split()
EXCEPTIONS = ("clown fish", "clown car", "trash can", "trash bin", "trash bag", "take out the trash", "garbage collection", "garbage collector", "garbage can", "sore loser award", "stupid mistake of mine", "worthless check", "class clown")
HOMOGLYPHS = {
    "а": "a", "α": "a", "ɑ": "a", "в": "b", "с": "c", "ϲ": "c", "ԁ": "d", "е": "e", "ε": "e", "є": "e", "ё": "e", "ɡ": "g", "һ": "h", "н": "h", "і": "i", "ι": "i", "ı": "i", "ӏ": "i", "ї": "i", "ј": "j", "к": "k", "κ": "k",
    "м": "m", "п": "n", "η": "n", "о": "o", "ο": "o", "σ": "o", "р": "p", "ρ": "p", "ԛ": "q", "г": "r", "ѕ": "s", "т": "t", "τ": "t", "υ": "u", "ս": "u", "ν": "v", "ѵ": "v", "ԝ": "w", "ω": "w", "х": "x", "χ": "x", "у": "y", "γ": "y", "ʏ": "y",
}
SUBSTITUTIONS = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "i", "|": "i", "€": "e", "l": "i", "+": "t"}
INVISIBLE = "­​‌‍⁠﻿"

#: Labelled training rows of each class that the lexicon and the curve are learnt from, chosen by a hash of the id.
LEARN_ROWS = 5000
MOST_WEIGHT = 8.0
PREFIXES = range(4, 9)
CUT = 0.7

_FOLD = {ord(k): v for k, v in (HOMOGLYPHS | SUBSTITUTIONS).items()}
_FOLD |= {0xFF01 + i: _FOLD.get(ord(chr(0x21 + i).lower()), chr(0x21 + i).lower()) for i in range(94)}  # full-width forms
_FOLD |= {ord(c): _FOLD.get(ord(c.lower()), c.lower()) for c in map(chr, range(0x41, 0x5B))}
_FOLD |= {ord(k.upper()): v for k, v in HOMOGLYPHS.items() if len(k.upper()) == 1 and ord(k.upper()) > 127}
_HIDDEN = re.compile(f"[{INVISIBLE}]")
_WORD = re.compile(r"[^\W\d_]+")


def shown(text: str) -> str:
    """The text without characters that do not show."""
    return text if text.isascii() else _HIDDEN.sub("", text)


def skeleton(text: str) -> str:
    """One character for each, in lower case, look-alikes made equal."""
    low = text.lower()
    return (low if len(low) == len(text) else text).translate(_FOLD)


@dataclass
class Lexicon:
    """terms: (skeleton, whole word or beginning of one) to weight; curve: intercept, slope of log weight, slope of log share."""

    terms: dict[tuple[str, bool], float] = field(default_factory=lambda: {(skeleton(w), True): 4.0 for w in SEEDS})
    exceptions: tuple[str, ...] = EXCEPTIONS
    curve: tuple[float, float, float] = (-4.0, 4.0, 0.5)

    def automaton(self) -> ahocorasick.Automaton:
        found = ahocorasick.Automaton()
        held: dict[str, list[tuple[str, float]]] = {}
        for (term, whole), weight in self.terms.items():
            held.setdefault(term, []).append(("word" if whole else "start", weight))
        for phrase in self.exceptions:
            held.setdefault(skeleton(phrase), []).append(("except", 0.0))
        for term, uses in held.items():
            found.add_word(term, (len(term), uses))
        if held:
            found.make_automaton()
        return found


def matches(text: str, automaton: ahocorasick.Automaton) -> list[tuple[int, int, float]]:
    """(begin, end, weight) of the matches that count, one for a word at most: the weightiest."""
    if not len(automaton):
        return []
    found: dict[int, tuple[int, float]] = {}
    spans: list[tuple[int, int]] = []
    for last, (size, uses) in automaton.iter(skeleton(text)):
        begin, end = last - size + 1, last + 1
        if begin and text[begin - 1].isalnum():
            continue
        closed = end == len(text) or not text[end].isalnum()
        for use, weight in uses:
            if use == "except":
                if closed:
                    spans.append((begin, end))
            elif (use == "start" or closed) and weight > found.get(begin, (0, -1.0))[1]:
                found[begin] = (end, weight)
    return [(b, e, w) for b, (e, w) in found.items() if not any(x <= b and e <= y for x, y in spans)]


def features(text: str | None, automaton: ahocorasick.Automaton) -> tuple[float, float]:
    """log(1 + weight of all matches) and log(1 + weight in a thousand words)."""
    text = shown(text or "")
    weight = sum(w for _, _, w in matches(text, automaton))
    if not weight:
        return 0.0, 0.0
    return float(np.log1p(weight)), float(np.log1p(1000 * weight / (1 + text.count(" ") + text.count("\n"))))


def chance(curve: tuple[float, float, float], x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(curve[0] + x @ np.array(curve[1:]), -30, 30)))


def terms_of(text: str | None) -> set[tuple[str, bool]]:
    """The words of a text and their beginnings, folded; learning chooses among these."""
    words = set(_WORD.findall(skeleton(shown(text or ""))))
    return {(w, True) for w in words if len(w) > 2} | {(w[:n], False) for w in words for n in PREFIXES if n <= len(w)}


def _count_terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for toxic, found in ((y, c) for batch in batches for y, c in _by_class(batch)):
        rows = list(found.items())
        yield pa.RecordBatch.from_arrays(
            [pa.array([t for (t, _), _ in rows], pa.string()), pa.array([w for (_, w), _ in rows], pa.bool_()), pa.array([n if toxic else 0 for _, n in rows], pa.int64()), pa.array([0 if toxic else n for _, n in rows], pa.int64())],
            names=["term", "whole", "pos", "neg"],
        )


def _by_class(batch: pa.RecordBatch) -> Iterator[tuple[bool, Counter]]:
    counts = {True: Counter(), False: Counter()}
    for part in slices(batch, "text", 2 << 20):
        for text, toxic in zip(part.column("text").to_pylist(), part.column("toxic").to_pylist()):
            counts[bool(toxic)].update(terms_of(text))
    yield from counts.items()


def chosen(found: list[tuple[str, bool, int, int]], n_pos: int, n_neg: int) -> dict[tuple[str, bool], float]:
    """Of (term, whole, toxic rows, other rows) the terms that are sure, without those that a longer or shorter one stands for."""
    sure: dict[tuple[str, bool], tuple[float, int]] = {}
    for term, whole, pos, neg in found:
        sure[term, whole] = (float(np.log((pos + 0.5) / (n_pos + 1)) - np.log((neg + 0.5) / (n_neg + 1))), pos)
    longer = lambda t: max((p for (u, w), (_, p) in by_start.get(t, ()) if (u, w) != (t, False)), default=0)
    by_start: dict[str, list] = {}
    for key, value in sure.items():
        for n in {*PREFIXES, len(key[0])}:
            if n <= len(key[0]):
                by_start.setdefault(key[0][:n], []).append((key, value))
    kept: dict[tuple[str, bool], float] = {}
    for (term, whole), (weight, pos) in sorted(sure.items(), key=lambda x: (len(x[0][0]), x[0])):
        if not whole and longer(term) >= 0.95 * pos:
            continue
        if any(kept.get((term[:n], False), -9.0) >= weight - 1.0 for n in range(1, len(term) + whole)):
            continue
        kept[term, whole] = min(weight, MOST_WEIGHT)
    return kept


def fitted(x: np.ndarray, y: np.ndarray) -> tuple[float, float, float]:
    """A logistic curve by Newton steps with a ridge; slopes are kept at 0 or more, so that more weight never lowers a score."""
    whole, use = np.column_stack([np.ones(len(x)), x]), [0, 1, 2]
    while True:
        b = np.zeros(3)
        for _ in range(50):
            p = 1 / (1 + np.exp(-np.clip(whole[:, use] @ b[use], -30, 30)))
            slope = whole[:, use].T @ (p - y) + 0.05 * b[use]
            bend = (whole[:, use] * (p * (1 - p))[:, None]).T @ whole[:, use] + 0.05 * np.eye(len(use))
            step = np.linalg.solve(bend, slope)
            b[use] -= step
            if np.abs(step).max() < 1e-8:
                break
        if (bad := [i for i in use if i and b[i] < 0]) == []:
            return tuple(float(v) for v in b)
        use = [i for i in use if i != bad[0]]


def _learnable():
    return F.coalesce(F.crc32(F.encode(F.col("doc_id").cast("string"), "UTF-8")) % 3 != 1, F.lit(False))


def learn(docs: DataFrame, labels: DataFrame, rows: int = LEARN_ROWS) -> Lexicon:
    """A lexicon from the labelled rows whose crc32(doc_id as text) mod 3 is not 1, `rows` of each class at most, chosen by a hash of the id.

    Labels that are null, and rows without text, teach nothing; a doc_id labelled twice is toxic if one label says so. Without both classes the seeds and the default curve stay."""
    ship(docs.sparkSession)
    marks = labels.filter("toxic is not null and doc_id is not null").groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic")).filter(_learnable())
    sizes = {r["toxic"]: r["count"] for r in marks.groupBy("toxic").count().collect()}
    n_pos, n_neg = sizes.get(1, 0), sizes.get(0, 0)
    base = Lexicon()
    if not n_pos or not n_neg:
        return base
    share = F.when(F.col("toxic") == 1, F.lit(min(1.0, rows / n_pos))).otherwise(F.lit(min(1.0, rows / n_neg)))
    picked = marks.filter(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) < share * (1 << 20))
    texts = docs.select("doc_id", "text").filter("text is not null").join(F.broadcast(picked), "doc_id")
    texts = spread(texts.select("text", "toxic"))
    n = {r["toxic"]: r["count"] for r in picked.groupBy("toxic").count().collect()}
    n_pos, n_neg = n.get(1, 0), n.get(0, 0)
    if not n_pos or not n_neg:
        return base
    counted = texts.mapInArrow(_count_terms, "term string, whole boolean, pos long, neg long").groupBy("term", "whole").agg(F.sum("pos").alias("pos"), F.sum("neg").alias("neg"))
    # how surely the term leans to toxic rows: Kullback-Leibler gain over the share of toxic rows, and a rate of 20 to 1
    p, q = F.col("pos") / (F.col("pos") + F.col("neg")), n_pos / (n_pos + n_neg)
    gain = F.col("pos") * F.log(p / q) + F.when(F.col("neg") > 0, F.col("neg") * F.log((1 - p) / (1 - q))).otherwise(0.0)
    odds = F.log((F.col("pos") + 0.5) / (n_pos + 1)) - F.log((F.col("neg") + 0.5) / (n_neg + 1))
    sure = counted.filter("pos >= 3").withColumn("gain", gain).filter((F.col("gain") >= 14) & (odds >= 3.0)).orderBy(F.desc("gain"), "term", "whole")
    found = [(r["term"], r["whole"], r["pos"], r["neg"]) for r in sure.collect()]
    lexicon = Lexicon(base.terms | chosen(found, n_pos, n_neg))
    held = docs.sparkSession.sparkContext.broadcast(lexicon)
    rows_of = texts.mapInArrow(lambda it: _feature_rows(it, held), "a double, b double, toxic int").toPandas()
    lexicon.curve = fitted(rows_of[["a", "b"]].to_numpy(), rows_of["toxic"].to_numpy(float))
    return lexicon


def _feature_rows(batches: Iterator[pa.RecordBatch], held) -> Iterator[pa.RecordBatch]:
    automaton = held.value.automaton()
    for whole in batches:
        for batch in slices(whole, "text"):
            x = np.array([features(t, automaton) for t in batch.column("text").to_pylist()]).reshape(-1, 2)
            yield pa.RecordBatch.from_arrays([pa.array(x[:, 0]), pa.array(x[:, 1]), batch.column("toxic")], names=["a", "b", "toxic"])


def _score_rows(batches: Iterator[pa.RecordBatch], held) -> Iterator[pa.RecordBatch]:
    automaton = held.value.automaton()
    for whole in batches:
        for batch in slices(whole, "text"):
            x = np.array([features(t, automaton) for t in batch.column("text").to_pylist()]).reshape(-1, 2)
            keep = [c for c in batch.schema.names if c != "text"]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), pa.array(chance(held.value.curve, x))], names=[*keep, "score"])


def score_documents(docs: DataFrame, lexicon: Lexicon) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every document; predicted is 1 from a score of 0.7.

    Null, empty and wordless texts score as texts without a match. A null doc_id counts as held out. Repeated rows each come back."""
    ship(docs.sparkSession)
    held = docs.sparkSession.sparkContext.broadcast(lexicon)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (~_learnable()).alias("held_out"), F.col("text").cast("string").alias("text"))
    scored = rows.mapInArrow(lambda it: _score_rows(it, held), "doc_id long, held_out boolean, score double")
    return scored.withColumn("predicted", (F.col("score") >= CUT).cast("int"))


def drop_toxic(docs: DataFrame, lexicon: Lexicon, cut: float = CUT) -> DataFrame:
    """docs, all columns, without the rows that score `cut` or more.

    Null, empty and wordless texts score as texts without a match, so they stay. Rows with a null doc_id are scored like any other, repeated rows stay
    or go together, other columns may have any names, and an empty table gives none."""
    ship(docs.sparkSession)
    held = docs.sparkSession.sparkContext.broadcast(lexicon)

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        automaton = held.value.automaton()
        for whole in batches:
            for batch in slices(whole, "text"):
                x = np.array([features(t, automaton) for t in batch.column("text").to_pylist()]).reshape(-1, 2)
                yield batch.filter(pa.array(chance(held.value.curve, x) < cut))

    return docs.mapInArrow(keep, docs.schema)

"""Benchmark decontamination: pigeonhole pieces of each item found exactly, then Myers' bit-parallel distance on the text around.

An item within an error budget of k edits of some stretch of a text has, of k + 1 pieces, one at least without an error there.
Aho-Corasick finds all pieces of all items in one pass over a text; each hit fixes where the item must lie, give or take k, and
the distance of the item to the best stretch in that window decides. Before that, the GROUP pieces around the hit must lie there
within fewer errors than there are pieces: as the item has fewer errors than pieces, so has one group at least, and a piece of it has none.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from landmark_kkm.llm.texts import slices
from landmark_kkm.session import ship

#: Edits allowed: one in EDIT_EVERY characters of the folded item; items of fewer than SHORT characters must occur as they are, between word ends.
EDIT_EVERY = 10
SHORT = 24
#: Bytes of items that are broadcast at a time; more items take more passes.
BROADCAST_BYTES = 16 << 20

GROUP = 4
#: Characters of the short runs that a group and the text around a hit are compared by first: an edit changes GRAM of a group's runs at most.
GRAM = 3

_WORD = re.compile(r"[^\W_]+")


def folded(text: str | None) -> str:
    """Lower-cased words of letters and digits, one space between."""
    return " ".join(_WORD.findall((text or "").lower()))


def budget(size: int, every: int = EDIT_EVERY) -> int:
    return 0 if size < SHORT else size // every


def pieces(item: str, errors: int) -> list[tuple[int, str]]:
    """(offset, piece): errors + 1 pieces of near equal length that make up the item."""
    cuts = [len(item) * i // (errors + 1) for i in range(errors + 2)]
    return [(a, item[a:b]) for a, b in zip(cuts, cuts[1:])]


def grams(text: str) -> set[str]:
    return {text[i : i + GRAM] for i in range(len(text) - GRAM + 1)}


def best_end(item: str, text: str) -> tuple[int, int]:
    """(distance, end) of the stretch of text that is nearest to the item, the first such end. Bit-parallel over the item: one step for each character of the text."""
    size = len(item)
    if not size:
        return 0, 0
    where: dict[str, int] = {}
    for i, c in enumerate(item):
        where[c] = where.get(c, 0) | 1 << i
    full, top = (1 << size) - 1, 1 << size - 1
    up, down, score = full, 0, size
    best = (size, 0)
    for at, c in enumerate(text, 1):
        eq = where.get(c, 0)
        vertical = eq | down
        diagonal = (((eq & up) + up) ^ up) | eq
        plus, minus = down | (full & ~(diagonal | up)), up & diagonal
        if plus & top:
            score += 1
        elif minus & top:
            score -= 1
        plus, minus = plus << 1 & full, minus << 1 & full
        up, down = minus | (full & ~(vertical | plus)), plus & vertical
        if score < best[0]:
            best = (score, at)
    return best


class Matcher:
    """Items (id, text), ready to be looked for."""

    def __init__(self, items: list[tuple[int, str]], every: int = EDIT_EVERY):
        self.every = every
        self.groups: list[list[tuple[int, str, int, set[str]]]] = []
        self.items = [(i, t) for i, t in ((i, folded(t)) for i, t in items) if t]
        uses: dict[str, list[tuple[int, int, int]]] = {}
        for n, (_, item) in enumerate(self.items):
            errors = budget(len(item), every)
            cut = pieces(item, errors)
            groups = max(1, len(cut) // GROUP)
            self.groups.append([])
            for g in range(groups):
                own = cut[len(cut) * g // groups : len(cut) * (g + 1) // groups]
                group = "".join(p for _, p in own)
                self.groups[n].append((own[0][0], group, len(own) - 1, grams(group)))
                for offset, piece in own:
                    uses.setdefault(piece, []).append((n, offset, g))
        self.automaton = ahocorasick.Automaton()
        for piece, found in uses.items():
            self.automaton.add_word(piece, (len(piece), found))
        if uses:
            self.automaton.make_automaton()

    @staticmethod
    def _near(text: str, start: int, offset: int, group: str, errors: int, runs: set[str]) -> bool:
        """Whether the group of pieces lies within its errors of where the item, begun at `start`, would have it."""
        if errors == 0 or not group:
            return True
        at = start + offset
        if text.startswith(group, max(at, 0)):
            return True
        window = text[max(0, at - errors) : at + len(group) + errors]
        if len(runs & grams(window)) < len(runs) - GRAM * errors:
            return False
        return best_end(group, window)[0] <= errors

    def find(self, text: str | None) -> dict[int, tuple[int, int]]:
        """item id to (distance, end in the folded text), for each item that the text holds within its budget."""
        text = folded(text)
        if not text or not self.items:
            return {}
        begins: dict[int, set[int]] = {}
        for last, (size, uses) in self.automaton.iter(text):
            for n, offset, g in uses:
                start = last - size + 1 - offset
                if start not in begins.get(n, ()) and self._near(text, start, *self.groups[n][g]):
                    begins.setdefault(n, set()).add(start)
        out: dict[int, tuple[int, int]] = {}
        for n, starts in begins.items():
            key, item = self.items[n]
            errors, best = budget(len(item), self.every), None
            if errors == 0:
                for at in sorted(starts):
                    if (at == 0 or text[at - 1] == " ") and text[at + len(item) : at + len(item) + 1] in ("", " "):
                        best = (0, at + len(item))
                        break
            else:
                for low, high in _windows(sorted(starts), errors):
                    a, b = max(0, low - errors), min(len(text), high + len(item) + errors)
                    at = text.find(item, a, b)
                    found = (0, at + len(item)) if at >= 0 else (lambda d, e: (d, a + e))(*best_end(item, text[a:b]))
                    if found[0] <= errors and (best is None or found < best):
                        best = found
                    if best and best[0] == 0:
                        break
            if best is not None and (key not in out or best < out[key]):
                out[key] = best
        return out


def _windows(starts: list[int], errors: int) -> Iterator[tuple[int, int]]:
    """Runs of start positions at most 2 * errors apart."""
    low = high = starts[0]
    for s in starts[1:]:
        if s - high > 2 * errors:
            yield low, high
            low = s
        high = s
    yield low, high


def _find_rows(batches: Iterator[pa.RecordBatch], held, every: int) -> Iterator[pa.RecordBatch]:
    matcher = Matcher(held.value, every)
    for whole in batches:
        for batch in slices(whole, "text"):
            ids, rows = batch.column("doc_id").to_pylist(), []
            for doc, text in zip(ids, batch.column("text").to_pylist()):
                rows += [(doc, item, distance, end) for item, (distance, end) in sorted(matcher.find(text).items())]
            columns = list(zip(*rows)) or [[], [], [], []]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.int64(), pa.int32(), pa.int64()))], names=["doc_id", "item_id", "distance", "end_at"])


def _passes(items: DataFrame, limit: int) -> Iterator[list[tuple[int, str]]]:
    # dealt by id, so that an item with several texts is looked for in one pass
    items = items.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).filter("item_id is not null and text is not null")
    size = items.agg(F.sum(F.octet_length("text") + 16)).first()[0] or 0
    count = -(-size // limit)
    for i in range(count):
        yield [tuple(r) for r in items.filter(F.pmod(F.xxhash64("item_id"), F.lit(count)) == i).collect()]


def contaminated(docs: DataFrame, items: DataFrame, broadcast_bytes: int = BROADCAST_BYTES, every: int = EDIT_EVERY) -> DataFrame:
    """(doc_id, item_id, distance, end_at): each document and each item that lies in it within one edit in `every` characters.

    Texts are compared as lower-cased words of letters and digits, one space between; end_at is where the nearest stretch ends in that form.
    Null, empty and wordless texts and items match nothing. An item id with several texts gives its nearest. Repeated documents each come back."""
    ship(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    ddl, found = "doc_id long, item_id long, distance int, end_at long", None
    for part in _passes(items, broadcast_bytes):
        held = docs.sparkSession.sparkContext.broadcast(part)
        one = rows.mapInArrow(lambda it, held=held: _find_rows(it, held, every), ddl)
        found = one if found is None else found.unionByName(one)
    return found if found is not None else docs.sparkSession.createDataFrame([], ddl)


def drop_contaminated(docs: DataFrame, items: DataFrame, every: int = EDIT_EVERY) -> DataFrame:
    """docs, all columns, without the rows that hold an item.

    Null, empty and wordless texts stay, rows with a null doc_id are looked at like any other, repeated rows stay or go together, other columns may have
    any names, and an empty table gives none. Items that are null, or have no words or no id, are looked for nowhere."""
    ship(docs.sparkSession)
    for part in _passes(items, BROADCAST_BYTES):
        held = docs.sparkSession.sparkContext.broadcast(part)

        def keep(batches: Iterator[pa.RecordBatch], held=held) -> Iterator[pa.RecordBatch]:
            matcher = Matcher(held.value, every)
            for whole in batches:
                for batch in slices(whole, "text"):
                    yield batch.filter(pa.array([not matcher.find(t) for t in batch.column("text").to_pylist()], pa.bool_()))

        docs = docs.mapInArrow(keep, docs.schema)
    return docs

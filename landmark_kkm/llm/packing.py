"""Best-fit packing of token sequences by a grouping genetic algorithm, at any number of documents.

Pieces of one length are alike, so what is packed is the histogram of lengths (as many entries as a sequence has tokens), and a packing
is a list of patterns: the lengths of a bin and how many bins hold them. Islands evolve such packings of the whole histogram, every length
in full count: crossover injects well-filled patterns of one parent into the other, removes what is then there too often and puts displaced
lengths back by best fit; elites migrate round a ring. Plain best fit is a member of the first population and the best member always
stays. Pieces find their places by their rank among those of the same length.
"""

from __future__ import annotations

import random
import zlib
from bisect import bisect_left, insort
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from landmark_kkm.llm.sharding import numbered, parts_of
from landmark_kkm.llm.texts import slices
from landmark_kkm.session import materialize, ship

CAPACITY = 1024
END_ID = 2
SPECIAL = "<|endoftext|>"
ISLANDS, POPULATION, EPOCHS, GENERATIONS = 4, 6, 4, 12


def default_tokenizer() -> tuple[str, str]:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_50k.tiktoken")


def encoder(json_path: str, ranks_path: str | None):
    """A function of texts to id lists. The ranks hold the same vocabulary for a faster library, which has no special tokens: texts that spell one go to the slower."""
    import base64

    from tokenizers import Tokenizer

    slow = Tokenizer.from_file(json_path)
    if ranks_path is None:
        return lambda texts: [e.ids for e in slow.encode_batch(texts, add_special_tokens=False)]
    import public_tokenizers
    import tiktoken

    with open(ranks_path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    fast = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    return lambda texts: [slow.encode(t, add_special_tokens=False).ids if SPECIAL in t else fast.encode_ordinary(t) for t in texts]


def cuts(size: int, capacity: int = CAPACITY) -> list[tuple[int, int]]:
    """(start, length) of a document's pieces: only the first may be shorter than the capacity."""
    first = size % capacity or capacity
    return [(0, first), *((at, capacity) for at in range(first, size, capacity))]


_ENCODERS: dict = {}


def _piece_rows(batches: Iterator[pa.RecordBatch], tokenizer: tuple[str, str | None], end_id: int, capacity: int) -> Iterator[pa.RecordBatch]:
    if tokenizer not in _ENCODERS:
        _ENCODERS[tokenizer] = encoder(*tokenizer)
    encode = _ENCODERS[tokenizer]
    for whole in batches:
        for batch in slices(whole, "text", 2 << 20):
            rows = []
            texts = [t or "" for t in batch.column("text").to_pylist()]
            for doc, ids in zip(batch.column("doc_id").to_pylist(), encode(texts)):
                data = np.array([*ids, end_id], dtype="<u4")
                rows += [(doc, i, at, n, zlib.crc32(data[at : at + n])) for i, (at, n) in enumerate(cuts(len(data), capacity))]
            columns = list(zip(*rows))
            types = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types)], names=["doc_id", "piece", "start", "length", "ids_crc32"])


# Patterns are (lengths of a bin, longest first; copies).
Patterns = list[tuple[tuple[int, ...], int]]


def best_fit(counts: dict[int, int], capacity: int, held: Patterns = (), rng: random.Random | None = None) -> Patterns:
    """The patterns held with all the lengths of counts, longest first, put where the least room is left; bins that hold the same stay one entry.

    With rng the longest lengths come a little out of order, so that members of a population differ."""
    open_bins: dict[int, list[list]] = {}  # room to [lengths, copies]
    rooms: list[int] = []

    def put(lengths: tuple[int, ...], copies: int) -> None:
        left = capacity - sum(lengths)
        if left not in open_bins:
            open_bins[left] = []
            insort(rooms, left)
        open_bins[left].append([lengths, copies])

    for lengths, copies in held:
        put(lengths, copies)
    order = sorted(counts, key=lambda s: -s * (rng.uniform(0.7, 1.0) if rng else 1))
    for size in order:
        count = counts[size]
        while count:
            at = bisect_left(rooms, size)
            if at == len(rooms):
                each = min(count, capacity // size)
                put((size,) * each, count // each)
                count -= count // each * each
                continue
            left = rooms[at]
            lengths, copies = open_bins[left].pop()
            if not open_bins[left]:
                del open_bins[left]
                rooms.pop(at)
            used = min(copies, count)
            if used < copies:
                put(lengths, copies - used)
            put((*lengths, size), used)
            count -= used
    return merged((tuple(sorted(lengths, reverse=True)), copies) for found in open_bins.values() for lengths, copies in found)


def merged(patterns) -> Patterns:
    total: Counter = Counter()
    for lengths, copies in patterns:
        total[lengths] += copies
    return sorted(((p, n) for p, n in total.items() if n), reverse=True)


def bins_of(patterns: Patterns) -> int:
    return sum(n for _, n in patterns)


def fitness(patterns: Patterns, capacity: int) -> float:
    """Mean squared fill: of packings with equally many bins, the one with fuller bins is nearer to saving one."""
    return sum(n * (sum(p) / capacity) ** 2 for p, n in patterns) / max(1, bins_of(patterns))


def _rank(patterns: Patterns, capacity: int) -> tuple[int, float]:
    return bins_of(patterns), -fitness(patterns, capacity)


def completed(kept: Patterns, counts: dict[int, int], capacity: int, rng: random.Random | None = None) -> Patterns:
    """As many of the kept patterns as counts allows, in turn, and best fit of all lengths that are left."""
    left, out = Counter(counts), []
    for pattern, copies in kept:
        need = Counter(pattern)
        copies = min(copies, min(left[s] // n for s, n in need.items()))
        if copies:
            out.append((pattern, copies))
            for s, n in need.items():
                left[s] -= n * copies
    return best_fit({s: n for s, n in left.items() if n}, capacity, out, rng)


def crossover(into: Patterns, of: Patterns, counts: dict[int, int], capacity: int, rng: random.Random) -> Patterns:
    """Well-filled patterns of one parent go whole into the other; of its bins those stay for which there are lengths left, the well-filled first. Displaced lengths are best-fitted."""
    full = [p for p in of if capacity - sum(p[0]) <= capacity // 64] or list(of)
    injected = rng.sample(full, rng.randint(1, max(1, len(full) // 2)))
    kept = sorted(into, key=lambda p: capacity - sum(p[0]))
    return completed([*injected, *kept[: max(1, len(kept) - rng.randint(0, 1 + len(kept) // 4))]], counts, capacity, rng if rng.random() < 0.5 else None)


def filled(counts: Counter, capacity: int, rng: random.Random, tries: int = 200) -> tuple[int, ...]:
    """Lengths that together fill a bin as far as a few random sets go, the longest that is left among them."""
    sizes = sorted((s for s, n in counts.items() if n), reverse=True)
    best: tuple[int, ...] = ()
    for _ in range(tries):
        own, room, used = [sizes[0]], capacity - sizes[0], Counter([sizes[0]])
        while True:
            fit = [s for s in sizes[bisect_left(sizes, -room, key=lambda s: -s) :] if counts[s] > used[s]]
            if not fit:
                break
            exact = [s for s in fit if room - s in counts and counts[room - s] > used[room - s] + (s == room - s)]
            s = fit[0] if fit[0] == room else rng.choice(exact or fit)
            own.append(s)
            used[s] += 1
            room -= s
        if sum(own) > sum(best):
            best = tuple(sorted(own, reverse=True))
        if room == 0:
            break
    return best


def mutated(patterns: Patterns, counts: dict[int, int], capacity: int, rng: random.Random) -> Patterns:
    """The emptiest patterns and a few others are emptied; some of their lengths are put together to fill bins, the rest is best-fitted."""
    kept = sorted(patterns, key=lambda p: capacity - sum(p[0]))
    kept = kept[: max(0, len(kept) - 1 - rng.randint(0, 1 + len(kept) // 8))]
    kept = [p for p in kept if rng.random() > 0.1]
    left = Counter(counts)
    for pattern, copies in kept:
        for s, n in Counter(pattern).items():
            left[s] -= n * copies
    more = []
    for _ in range(rng.randint(0, 12)):
        left = +left
        if not left:
            break
        own = filled(left, capacity, rng)
        need = Counter(own)
        copies = min(left[s] // n for s, n in need.items())
        more.append((own, copies))
        for s, n in need.items():
            left[s] -= n * copies
    return completed([*kept, *more], counts, capacity, rng if rng.random() < 0.3 else None)


def evolved(population: list[Patterns], counts: dict[int, int], capacity: int, generations: int, seed: int) -> list[Patterns]:
    """The population after some generations, best first. A child replaces the worst member that it betters."""
    rng = random.Random(seed)
    population = sorted(population, key=lambda p: _rank(p, capacity))
    for _ in range(generations):
        for _ in range(len(population)):
            a, b = rng.sample(population, 2) if len(population) > 1 else (population[0], population[0])
            child = crossover(a, b, counts, capacity, rng)
            if rng.random() < 0.7:
                child = mutated(child, counts, capacity, rng)
            if _rank(child, capacity) < _rank(population[-1], capacity) and child not in population:
                population[-1] = child
                population.sort(key=lambda p: _rank(p, capacity))
    return population


def started(counts: dict[int, int], capacity: int, count: int, seed: int) -> list[Patterns]:
    """First members: plain best fit, and best fit of the lengths a little out of order."""
    rng = random.Random(seed)
    return [best_fit(counts, capacity), *(best_fit(counts, capacity, rng=rng) for _ in range(count - 1))]


def plan(spark, counts: dict[int, int], capacity: int = CAPACITY, islands: int = ISLANDS, population: int = POPULATION, epochs: int = EPOCHS, generations: int = GENERATIONS) -> Patterns:
    """Patterns that use each length exactly as often as counts says, in as few bins as the islands find.

    Each epoch is one Spark job with a task for each island; what it moves is bounded by the patterns of a packing, of which there are no more than
    lengths by far, whatever the counts. Islands stop at the least number of bins that the tokens need."""
    counts = {int(s): int(n) for s, n in counts.items() if n}
    out: Patterns = [((capacity,), counts.pop(capacity))] if capacity in counts else []
    if not counts:
        return out
    state = [started(counts, capacity, population, seed) for seed in range(islands)]
    least = -(-sum(s * n for s, n in counts.items()) // capacity)
    best = lambda: min((m for members in state for m in members), key=lambda p: _rank(p, capacity))

    def evolve(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for number, part in pd.concat([*parts, pd.DataFrame({"island": []})]).groupby("island"):
            members = [[(tuple(p), int(n)) for p, n in zip(ps, ns)] for ps, ns in zip(part["bins"], part["copies"])]
            found = evolved(members, counts, capacity, generations, int(part["seed"].iloc[0]))
            yield pd.DataFrame({"island": int(number), "seed": 0, "bins": [[list(p) for p, _ in m] for m in found], "copies": [[n for _, n in m] for m in found]})

    ddl = "island int, seed int, bins array<array<int>>, copies array<long>"
    for epoch in range(epochs):
        if bins_of(best()) == least:
            break
        rows = [(i, epoch * islands + i, [list(p) for p, _ in m], [n for _, n in m]) for i, members in enumerate(state) for m in members]
        found: dict[int, list[Patterns]] = {}
        for r in spark.createDataFrame(rows, ddl).repartitionById(islands, "island").mapInPandas(evolve, ddl).collect():
            found.setdefault(r["island"], []).append([(tuple(p), n) for p, n in zip(r["bins"], r["copies"])])
        state = [sorted(found[i], key=lambda p: _rank(p, capacity)) for i in range(islands)]
        elites = [members[0] for members in state]
        state = [sorted([*members[:-1], elites[i - 1]], key=lambda p: _rank(p, capacity)) for i, members in enumerate(state)]  # round the ring
    return out + best()


class Places:
    """Where the r-th piece of a length goes, for all lengths; sorted ranges of ranks, looked up for many pieces at a time."""

    def __init__(self, patterns: Patterns):
        rank: Counter = Counter()
        rows = []
        first = 0
        for lengths, copies in patterns:
            offset = 0
            for size, each in sorted(Counter(lengths).items(), reverse=True):
                rows.append((size, rank[size], first, each, offset))
                rank[size] += each * copies
                offset += size * each
            first += copies
        rows.sort()
        table = np.array(rows, dtype=np.int64).reshape(-1, 5)
        self.size, self.low, self.first, self.each, self.offset = (np.ascontiguousarray(c) for c in table.T)
        self.begin = np.searchsorted(self.size, np.arange((self.size.max() if len(table) else 0) + 2))

    def find(self, size: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(bin, offset) of each piece."""
        key = self.size << 40 | self.low
        at = np.searchsorted(key, size << 40 | rank, side="right") - 1
        within = rank - self.low[at]
        return self.first[at] + within // self.each[at], self.offset[at] + within % self.each[at] * size


def _place_rows(batches: Iterator[pa.RecordBatch], held) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        sequence, offset = held.value.find(batch.column("length").to_numpy(), batch.column("rank").to_numpy())
        keep = batch.schema.names[:-1]
        yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), pa.array(sequence), pa.array(offset)], names=[*keep, "sequence_id", "offset"])


def pack_documents(docs: DataFrame, tokenizer: tuple[str, str | None] | None = None, end_id: int = END_ID, capacity: int = CAPACITY, **how) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32, sequence_id, offset): the pieces of every document and their places.

    A document is its text's ids and the end id; null and empty texts are the end id alone. Documents over the capacity are cut into pieces of the
    capacity, the first shorter. No two pieces overlap and sequences have no gaps. Repeated rows and null ids are packed each. An empty table gives no rows."""
    spark = docs.sparkSession
    ship(spark)
    tokenizer = tokenizer or default_tokenizer()
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    ddl = "doc_id long, piece int, start long, length long, ids_crc32 long"
    pieces = materialize(rows.mapInArrow(lambda it: _piece_rows(it, tokenizer, end_id, capacity), ddl), "pieces")
    counts = {r["length"]: r["count"] for r in pieces.groupBy("length").count().collect()}
    held = spark.sparkContext.broadcast(Places(plan(spark, counts, capacity, **how)))
    parts = F.get(F.array(*[F.lit(parts_of(counts.get(n, 0))) for n in range(capacity + 1)]), F.col("length").cast("int"))
    ranked = numbered(pieces, "length", [F.col("doc_id"), F.col("piece"), F.col("ids_crc32")], "rank", parts)
    ranked = ranked.select("doc_id", "piece", "start", "length", "ids_crc32", "rank")
    return ranked.mapInArrow(lambda it: _place_rows(it, held), f"{ddl}, sequence_id long, offset long")

"""SimHash near-duplicates: fingerprints, BK-trees over shards of fingerprints, components.

Trees are not broadcast: all fingerprints together have no size bound. A pigeonhole key sends each fingerprint to every shard
that any partner within the radius must share (near copies by similarity: to the shards of its bands of least hashes), and each task builds the trees of its shards and follows only the edges whose
key lies within the radius of the query's distance. The pairs found in a shard leave it as a spanning forest, never as all pairs.
Where copies are meant by similarity, what trees find are candidates only: their texts meet by components of candidates, and the shingle sets decide.
A shard or component that is too large for a task is cut into blocks, and each two blocks meet in a task of their own: memory stays bounded and no link is lost.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from landmark_kkm.llm.components import components
from landmark_kkm.llm.texts import as_bytes, mix, shingle_hashes, slices, whole_groups, words_of
from landmark_kkm.session import materialize, ship

BITS = 64
#: Expected fingerprints in a shard, above which a longer key is taken.
SHARD_ROWS = 64
#: Columns of the wide fingerprint, 64 bits each.
WIDE = [f"w{j}" for j in range(16)]
#: Eight lanes of a byte, for counting bits 0, 8, 16, ... of 64 at once; a lane counts up to 255 hashes.
LANES, LANE_ROWS, CHUNK = np.uint64(0x0101010101010101), 255, 1 << 13
#: Hashes up to which bits are unpacked instead.
FEW = 800
#: Bands of least hashes that choose the shards of near copies. At a similarity s two texts share a band with probability 1 - (1 - s**4)**16: 0.9998 at 0.8.
BANDS, BAND_ROWS = 16, 4
#: Fingerprints of a shard, and shingle hashes of a component, that one block holds; a task holds two.
BLOCK_PRINTS, BLOCK_HASHES = 200_000, 1 << 21
#: Near copies share 4 of 5 of their shingles.
SHARED, PARTS = 4, 5


def majorities(hashes: np.ndarray) -> np.ndarray:
    """The 64-bit fingerprint of each row of hashes (rows, n): a bit is 1 if set in over half of the n; 0 for no hashes."""
    rows, n = hashes.shape
    if rows * n <= FEW:
        bits = np.unpackbits(np.ascontiguousarray(hashes).view(np.uint8).reshape(rows, n, 8), axis=2, bitorder="little")
        return np.packbits(2 * bits.sum(1, dtype=np.int64) > n, axis=1, bitorder="little").view(np.uint64).ravel()
    count = np.zeros((rows, 8, 8), np.int64)
    for at in range(0, n, CHUNK):
        part = hashes[:, at : at + CHUNK]
        cuts = np.arange(0, part.shape[1], LANE_ROWS)
        for bit in range(8):
            lanes = np.add.reduceat((part >> np.uint64(bit)) & LANES, cuts, axis=1)
            count[:, :, bit] += lanes.view(np.uint8).reshape(rows, len(cuts), 8).sum(1, dtype=np.int64)
    return np.packbits(2 * count.reshape(rows, BITS) > n, axis=1, bitorder="little").view(np.uint64).ravel()


def majority(hashes: np.ndarray) -> int:
    return int(majorities(hashes[None])[0])


def wide_majorities(hashes: np.ndarray) -> np.ndarray:
    """The wide fingerprint: one word of 64 bits for each of the salts that the hashes are mixed with."""
    return majorities(np.stack([mix(hashes, j + 1) for j in range(len(WIDE))]))


def band_keys(hashes: np.ndarray) -> np.ndarray:
    """One key for each band: a hash of BAND_ROWS least hashes, each under another order (the hashes times an odd word: xor would deal the few hashes of a short text too unevenly)."""
    orders = mix(np.arange(BANDS * BAND_ROWS, dtype=np.uint64), 7) | np.uint64(1)
    least = np.full(len(orders), np.iinfo(np.uint64).max)
    for at in range(0, len(hashes), CHUNK):
        np.minimum(least, (hashes[None, at : at + CHUNK] * orders[:, None]).min(1), out=least)
    least = least.reshape(BANDS, BAND_ROWS)
    key = np.arange(BANDS, dtype=np.uint64)
    for j in range(BAND_ROWS):
        key = mix(key ^ least[:, j], j + 1)
    return key


def _fingerprint_batches(batches: Iterator[pa.RecordBatch], width: int, wide: bool, keep: list[str]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for batch in slices(whole, "text"):
            prints, more, sizes, bands = [], [[] for _ in WIDE], [], []
            for text in as_bytes(batch.column("text")):
                hashes = shingle_hashes(words_of(text), width)
                if wide:
                    hashes = np.unique(hashes)
                    prints.append(majority(hashes))
                    sizes.append(len(hashes))
                    for column, word in zip(more, wide_majorities(hashes)):
                        column.append(word)
                    bands.append(band_keys(hashes))
                else:
                    prints.append(majority(hashes))
            columns = [batch.column(k) for k in keep] + [pa.array(np.array(x, dtype=np.uint64).view(np.int64)) for x in ([prints, *more, sizes] if wide else [prints])]
            if wide:
                keys = np.concatenate(bands).view(np.int64)
                columns.append(pa.ListArray.from_arrays(pa.array(np.arange(0, len(keys) + 1, BANDS, dtype=np.int32)), pa.array(keys)))
            yield pa.RecordBatch.from_arrays(columns, names=[*keep, "fp", *([*WIDE, "size", "bands"] if wide else [])])


def fingerprints(docs: DataFrame, width: int = 4, wide: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fp) of every row, fp a signed view of the 64 bits. Null and wordless texts get 0.

    wide: fp is taken over the distinct shingles, of which there are `size`, and w0 to w15 hold 1024 bits more, whose differing
    share estimates the angle between shingle sets; bands holds the keys of its shards.
    """
    ship(docs.sparkSession)
    schema = "doc_id long, fp long" + ("".join(f", {w} long" for w in WIDE) + ", size long, bands array<long>" if wide else "")
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(lambda it: _fingerprint_batches(it, width, wide, ["doc_id"]), schema)


def blocks_for(count: int, radius: int) -> int:
    """The fewest blocks such that shards of `count` fingerprints hold about SHARD_ROWS each; radius + 1 blocks at least.

    Of b blocks, any two fingerprints within the radius agree on b - radius at least; there are comb(b, radius) keys for each."""
    blocks = radius + 1
    while count > SHARD_ROWS * 2 ** (BITS * (blocks - radius) / blocks) and comb(blocks + 1, radius) <= 500:
        blocks += 1
    return blocks


def masks_for(blocks: int, radius: int) -> list[int]:
    """One mask of the agreeing bits for each choice of agreeing blocks, as signed longs."""
    edges = [round(BITS * i / blocks) for i in range(blocks + 1)]
    block = [sum(1 << bit for bit in range(a, b)) for a, b in zip(edges, edges[1:])]
    whole = [sum(block[i] for i in chosen) for chosen in combinations(range(blocks), blocks - radius)]
    return [m - (1 << 64) if m >> 63 else m for m in whole]


class Forest:
    """BK-trees over runs of equal shard keys, held in arrays; every row is a node, the first row of a run its root."""

    def __init__(self, prints: np.ndarray, starts: np.ndarray):
        self.prints = prints
        n = len(prints)
        self.root = np.repeat(starts, np.diff(np.append(starts, n)))
        parent, edge = np.full(n, -1, np.int64), np.zeros(n, np.int64)
        moving = np.flatnonzero(self.root != np.arange(n))
        at = self.root[moving]
        while len(moving):
            distance = np.bitwise_count(prints[moving] ^ prints[at]).astype(np.int64)
            slot = at * (BITS + 1) + distance
            order = np.argsort(slot, kind="stable")
            moving, slot, at, distance = moving[order], slot[order], at[order], distance[order]
            first = np.append(True, slot[1:] != slot[:-1])
            child = moving[first]
            parent[child], edge[child] = at[first], distance[first]
            at = np.repeat(child, np.diff(np.append(np.flatnonzero(first), len(moving))))[~first]
            moving = moving[~first]
        self.nodes = np.flatnonzero(parent >= 0)
        self.nodes = self.nodes[np.argsort(parent[self.nodes], kind="stable")]
        self.edge = edge[self.nodes]
        self.begin = np.searchsorted(parent[self.nodes], np.arange(n + 1))

    def earlier_within(self, queries: np.ndarray, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Arrays (query, node) of all pairs within the radius whose node comes before the query in the same tree."""
        q, node = queries, self.root[queries]
        q, node = q[node < q], node[node < q]
        stack = [(q, node)]
        while stack:
            q, node = stack.pop()
            if len(q) > 1 << 20:
                half = len(q) // 2
                stack += [(q[:half], node[:half]), (q[half:], node[half:])]
                continue
            if not len(q):
                continue
            distance = np.bitwise_count(self.prints[q] ^ self.prints[node]).astype(np.int64)
            near = distance <= radius
            if near.any():
                yield q[near], node[near]
            a, b = self.begin[node], self.begin[node + 1]
            fan = b - a
            if not fan.any():
                continue
            total = int(fan.sum())
            if total > 1 << 22 and len(q) > 1:
                half = len(q) // 2
                for part in (slice(0, half), slice(half, None)):
                    stack.append(self._children(q[part], a[part], fan[part], distance[part], radius))
                continue
            stack.append(self._children(q, a, fan, distance, radius))

    def _children(self, q, a, fan, distance, radius):
        total = int(fan.sum())
        at = np.arange(total) - np.repeat(np.cumsum(fan) - fan, fan) + np.repeat(a, fan)
        q, distance = np.repeat(q, fan), np.repeat(distance, fan)
        child = self.nodes[at]
        keep = (np.abs(self.edge[at] - distance) <= radius) & (child < q)
        return q[keep], child[keep]


def unite(label: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Join the classes of the pairs (a, b); label holds the least member of each row's class afterwards, or leads to it."""
    while True:
        x, y = label[a], label[b]
        apart = x != y
        if not apart.any():
            return
        np.minimum.at(label, np.maximum(x[apart], y[apart]), np.minimum(x[apart], y[apart]))
        while True:
            up = label[label]
            if (up == label).all():
                break
            label[:] = up


def _shard_labels(table: pa.Table, radius: int, wide_radius: int | None) -> tuple[np.ndarray, np.ndarray]:
    """(rep, label) of a table of whole shards; label is the first row of the class that links within the radius make in a shard."""
    key = table.column("shard").to_numpy()
    rep = table.column("rep").to_numpy()
    prints = table.column("fp").to_numpy().view(np.uint64)
    wide = [table.column(w).to_numpy().view(np.uint64) for w in WIDE] if wide_radius is not None else []
    size = table.column("size").to_numpy() if wide else None
    starts = np.flatnonzero(np.append(True, key[1:] != key[:-1]))
    forest, label = Forest(prints, starts), np.arange(len(key))
    for q, node in forest.earlier_within(np.arange(len(key)), radius):
        if wide:
            small, large = np.minimum(size[q], size[node]), np.maximum(size[q], size[node])
            near = PARTS * small >= SHARED * large  # no similarity is above the ratio of the sizes
            q, node = q[near], node[near]
            near = sum(np.bitwise_count(w[q] ^ w[node]).astype(np.int64) for w in wide) <= wide_radius
            q, node = q[near], node[near]
        unite(label, q, node)
    return rep, label


def _forest_edges(batches: Iterator[pa.RecordBatch], radius: int, wide_radius: int | None = None) -> Iterator[pa.RecordBatch]:
    for table in whole_groups(batches, "shard"):
        rep, label = _shard_labels(table, radius, wide_radius)
        linked = np.flatnonzero(label != np.arange(len(label)))
        yield pa.RecordBatch.from_arrays([pa.array(rep[linked]), pa.array(rep[label[linked]])], names=["u", "v"])


def celled(rows: DataFrame, key: str, blocks: DataFrame) -> DataFrame:
    """rows with `key` as it is, or for the keys that blocks (key, k) names a key for each two of their k blocks, a row going to each cell of its own block."""
    own = F.pmod(F.xxhash64("rep"), F.col("_k")).cast("int")
    cells = F.transform(F.sequence(F.lit(0), F.col("_k") - 1), lambda j: F.xxhash64(F.col(key), F.least(own, j), F.greatest(own, j)))
    met = rows.join(F.broadcast(blocks.select(F.col(key).alias("_key"), F.col("k").cast("int").alias("_k"))), F.col(key) == F.col("_key"), "left")
    return met.withColumn(key, F.explode(F.when(F.col("_k") > 1, cells).otherwise(F.array(F.col(key))))).drop("_key", "_k")


def hot(rows: DataFrame, key: str, weight, limit: int) -> DataFrame:
    """(key, k) of the keys whose weights add up to more than the limit, in k blocks. There are fewer of them than the whole weight over the limit."""
    blocks = rows.groupBy(key).agg(F.sum(weight).alias("_w")).filter(F.col("_w") > limit)
    return materialize(blocks.select(key, F.ceil(F.col("_w") / limit).alias("k")), "hot")


def _set_batches(batches: Iterator[pa.RecordBatch], width: int) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for batch in slices(whole, "text"):
            sets = [np.unique(shingle_hashes(words_of(text), width)).view(np.int64) for text in as_bytes(batch.column("text"))]
            ends = np.cumsum([0, *map(len, sets)])
            yield pa.RecordBatch.from_arrays([batch.column("rep"), batch.column("grp"), pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(np.concatenate(sets)))], names=["rep", "grp", "hashes"])


def similar(values: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The classes that links of similarity SHARED / PARTS or more make of the sets that lie one after the other in values: the least member of each set's class.

    A set is compared with all others at once, by the sets that have its hashes. Those of the largest class need no comparison: what links them to a
    set outside is found from there."""
    label, ends = np.arange(len(sizes)), np.cumsum(sizes)
    order = np.argsort(values, kind="stable")
    first = np.append(True, values[order][1:] != values[order][:-1])
    owner = np.repeat(label, sizes)[order]  # of each hash in turn, the sets that have it
    begin = np.flatnonzero(first)
    count = np.diff(np.append(begin, len(values)))
    run = np.empty(len(values), np.int64)
    run[order] = np.cumsum(first) - 1
    waiting = np.ones(len(sizes), bool)
    while True:
        largest = np.bincount(label).argmax()
        outside = np.flatnonzero(waiting & (label != largest))
        if not len(outside):
            return label
        i = outside[0]
        waiting[i] = False
        mine = run[ends[i] - sizes[i] : ends[i]]
        fan = count[mine]
        at = np.arange(fan.sum()) - np.repeat(np.cumsum(fan) - fan, fan) + np.repeat(begin[mine], fan)
        shared = np.bincount(owner[at], minlength=len(sizes))
        near = np.flatnonzero((shared > 0) & (PARTS * shared >= SHARED * (sizes[i] + sizes - shared)))
        unite(label, np.full(len(near), i), near)


def _confirmed_edges(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for table in whole_groups(batches, "grp", 2000):
        key, rep = table.column("grp").to_numpy(), table.column("rep").to_numpy()
        lists = table.column("hashes").combine_chunks()
        values, sizes = lists.flatten().to_numpy(), lists.value_lengths().to_numpy().astype(np.int64)
        ends = np.append(0, np.cumsum(sizes))
        starts = np.flatnonzero(np.append(True, key[1:] != key[:-1]))
        label = np.concatenate([a + similar(values[ends[a] : ends[b]], sizes[a:b]) for a, b in zip(starts, np.append(starts[1:], len(key)))])
        linked = np.flatnonzero(rep[label] != rep)
        yield pa.RecordBatch.from_arrays([pa.array(rep[linked]), pa.array(rep[label[linked]])], names=["u", "v"])


def _pigeonhole_shards(nodes: DataFrame, radius: int) -> DataFrame:
    """nodes with shard, once for each key of agreeing blocks: any two within the radius meet in one shard at least."""
    masks = masks_for(blocks_for(nodes.count(), radius), radius)
    return nodes.withColumn("shard", F.explode(F.array(*[F.xxhash64(F.lit(i), F.col("fp").bitwiseAND(F.lit(m).cast("long"))) for i, m in enumerate(masks)])))


def _tasks(rows: DataFrame) -> int:
    return max(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), rows.sparkSession.sparkContext.defaultParallelism)


def _linked(shards: DataFrame, radius: int, wide_radius: int | None, block: int) -> DataFrame:
    """Edges (u, v): a spanning forest of the links of each shard. shards: (shard, rep, fp, and what else the links need)."""
    cells = celled(shards, "shard", hot(shards, "shard", F.lit(1), block))
    return cells.repartition(_tasks(shards), "shard").sortWithinPartitions("shard", "rep").mapInArrow(lambda it: _forest_edges(it, radius, wide_radius), "u long, v long")


def link(prints: DataFrame, radius: int, block: int = BLOCK_PRINTS) -> DataFrame:
    """prints with component_id: the least doc_id reachable over links of at most `radius` differing bits.

    Equal fingerprints are one node; a null doc_id takes the component of its fingerprint."""
    nodes = materialize(prints.filter("doc_id is not null").groupBy("fp").agg(F.min("doc_id").alias("rep")), "nodes")
    return _labelled(prints, nodes, components(_linked(_pigeonhole_shards(nodes, radius), radius, None, block)), ["fp"])


def link_similar(prints: DataFrame, docs: DataFrame, width: int, radius: int, wide_radius: int, block: int = BLOCK_PRINTS, block_hashes: int = BLOCK_HASHES) -> DataFrame:
    """prints (wide) with component_id: the least doc_id reachable over links of a shingle-set similarity of SHARED / PARTS or more.

    Candidates share a band (at that similarity with a chance of 0.9998; a text goes to BANDS shards however many texts there are), differ in at most
    `radius` bits of fp and `wide_radius` of the wide ones. Components of candidates get the shingle sets of their texts, taken once from docs
    (doc_id, text), and a link is made where the sets say so. Equal fingerprints are one node."""
    same = ["fp", *WIDE, "size"]
    least = prints.groupBy(*same).agg(F.min(F.struct("doc_id", "bands")).alias("least"))
    nodes = materialize(least.select(*same, F.col("least.doc_id").alias("rep"), "least.bands"), "nodes")
    candidates = components(_linked(nodes.select(*same, "rep", F.explode("bands").alias("shard")), radius, wide_radius, block))
    candidates = materialize(candidates.join(nodes.select("rep", "size"), F.col("node") == F.col("rep")).select("rep", F.col("component").alias("grp"), "size"), "candidates")
    blocks = hot(candidates, "grp", F.col("size"), block_hashes)
    named = candidates.select("rep", "grp").hint("merge")  # one plan at every size: a broadcast of reps would grow with the corpus
    texts = docs.select(F.col("doc_id").cast("long").alias("rep"), F.col("text").cast("string").alias("text")).join(named, "rep")
    sets = texts.mapInArrow(lambda it: _set_batches(it, width), "rep long, grp long, hashes array<long>").filter(F.size("hashes") > 0)
    dealt = celled(sets, "grp", blocks).repartition(_tasks(nodes), "grp").sortWithinPartitions("grp", "rep")
    return _labelled(prints, nodes, components(dealt.mapInArrow(_confirmed_edges, "u long, v long")), same)


def _labelled(prints: DataFrame, nodes: DataFrame, found: DataFrame, same: list[str]) -> DataFrame:
    reps = nodes.join(found, nodes.rep == found.node, "left").select(*same, F.coalesce("component", "rep").alias("component_id"))
    return prints.join(reps, same, "left")


def near_duplicates(docs: DataFrame, radius: int = 4, width: int = 4) -> DataFrame:
    """(doc_id, fingerprint, component_id) of every document.

    Nulls and wordless texts have the fingerprint zero and link like any other. Repeated rows each come back, a null doc_id with
    the component of its fingerprint (null if no other row has it). Other columns are ignored; an empty table gives no rows."""
    prints = materialize(fingerprints(docs, width), "prints")
    return link(prints, radius).select(
        "doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id"
    )


#: Differing bits of 1024 at a shingle-set similarity of 0.8: cosine 0.8 * 2 / 1.8, angle 0.476, 1024 * 0.476 / pi = 155.2, plus three quarters of a deviation (11.5).
WIDE_RADIUS = 164
#: Differing bits of a candidate pair: no shape of two sets at 0.8 has a mean above 165 of 1024 from six shingles on, or 192 with fewer (ties of the
#: majority count as 0), so this is six deviations and more above it, or nearly four; and of 64 bits, four and a half above the mean of 12.
CANDIDATE_WIDE, CANDIDATE_RADIUS = WIDE_RADIUS + 76, 26


def drop_near_duplicates(docs: DataFrame, width: int = 5, radius: int = CANDIDATE_RADIUS, wide_radius: int = CANDIDATE_WIDE) -> DataFrame:
    """docs without all but the least doc_id of each group of near copies (links of an exact similarity of five-word shingle sets of 0.8 or more).

    Rows without words, which have no shingle to compare, and rows with a null doc_id stay. Of repeated rows of one doc_id that stays, all stay."""
    prints = materialize(fingerprints(docs, width, wide=True).filter("doc_id is not null and size > 0"), "prints")
    drop = link_similar(prints, docs, width, radius, wide_radius).filter("doc_id <> component_id").select(F.col("doc_id").alias("gone")).distinct()
    drop = materialize(drop, "gone")
    return docs.join(drop, docs["doc_id"] == drop["gone"], "left_anti")

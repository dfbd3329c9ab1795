"""Corpus operators against brute force, round trips and held-out accuracy; nulls, ties, empty tables and odd columns."""

import hashlib
import zlib
from collections import Counter
from math import log10

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from landmark_kkm.llm import decontaminate, langid, linededup, packing, ppm, sharding, simhash, sketches, toxicity, warc
from landmark_kkm.llm.components import components

DDL = "doc_id long, text string, lang string, source string, n_chars long"


def frame(spark, texts, first=0):
    rows = [(first + i, t, "en", "s", len(t) if t is not None else None) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, DDL)


ODD = [None, "", " \t\n ", "a", "a", "one two three", "x" * 5000, "wörd " * 3000, "line\nline\n\nline", "\u0000nul \x0b tab", "a"]


def test_components_match_union_find(spark):
    rng = np.random.default_rng(1)
    edges = [(int(a), int(b)) for a, b in rng.integers(0, 400, (250, 2))] + [(i, i + 1) for i in range(1000, 1100)]
    label = {}

    def find(x):
        while label.setdefault(x, x) != x:
            x = label[x]
        return x

    for a, b in edges:
        x, y = find(a), find(b)
        label[max(x, y)] = min(x, y)
    found = dict(components(spark.createDataFrame(edges, "u long, v long")).collect())
    assert found == {n: find(n) for e in edges if e[0] != e[1] for n in e}


def test_components_of_no_edges(spark):
    assert components(spark.createDataFrame([], "u long, v long")).count() == 0


def brute_fingerprint(text, width=4):
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    grams = [b" ".join(words[i : i + width]) for i in range(max(1, len(words) - width + 1))]
    h = [xxhash.xxh64_intdigest(g, 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def test_fingerprints_and_components_match_brute_force(spark):
    rng = np.random.default_rng(0)
    base = [" ".join(f"w{rng.integers(40)}" for _ in range(rng.integers(3, 60))) for _ in range(25)]
    texts = ODD + base + [b.replace("w1 ", "w2 ", 1) for b in base] + base[:5]
    found = {r.doc_id: r for r in simhash.near_duplicates(frame(spark, texts), 4, 4).collect()}
    prints = [brute_fingerprint(t) for t in texts]
    assert [int(found[i].fingerprint, 16) for i in range(len(texts))] == prints
    group = list(range(len(texts)))
    for _ in range(len(texts)):
        group = [min(group[j] for j in range(len(texts)) if (prints[i] ^ prints[j]).bit_count() <= 4) for i in range(len(texts))]
    assert [found[i].component_id for i in range(len(texts))] == group


@pytest.mark.parametrize("n", [0, 1, 2, 255, 256, 511, simhash.CHUNK + 300])
def test_majorities_count_every_hash(n):
    hashes = np.random.default_rng(n).integers(0, 1 << 64, (3, n), dtype=np.uint64)
    bits = (hashes[:, :, None] >> np.arange(64, dtype=np.uint64)) & np.uint64(1)
    brute = [sum(1 << b for b in range(64) if 2 * int(row[:, b].sum()) > n) for row in bits]
    assert simhash.majorities(hashes).tolist() == brute
    assert [simhash.majority(row) for row in hashes] == brute


def test_similar_sets_share_a_band_and_others_do_not():
    rng, met, strange = np.random.default_rng(6), 0, 0
    for n in (1, 9, 400, simhash.CHUNK + 90):
        for _ in range(25):
            shared = rng.integers(0, 1 << 64, n, dtype=np.uint64)
            mine, other = (np.concatenate([shared, rng.integers(0, 1 << 64, n // 9, dtype=np.uint64)]) for _ in range(2))
            met += bool((simhash.band_keys(mine) == simhash.band_keys(other)).any())
            strange += bool((simhash.band_keys(mine) == simhash.band_keys(rng.integers(0, 1 << 64, n, dtype=np.uint64))).any())
    assert met == 100 and strange == 0
    assert len(simhash.band_keys(np.zeros(0, np.uint64))) == simhash.BANDS


def test_wide_fingerprints_tell_similarities_apart():
    rng, near, far = np.random.default_rng(5), 0, 0
    for _ in range(50):
        shared = rng.integers(0, 1 << 64, 400, dtype=np.uint64)
        other = lambda n: np.concatenate([shared, rng.integers(0, 1 << 64, n, dtype=np.uint64)])
        apart = lambda n: sum(int(np.bitwise_count(a)) for a in simhash.wide_majorities(other(n)) ^ simhash.wide_majorities(other(n)))
        near += apart(22) <= simhash.WIDE_RADIUS  # a similarity of 0.9
        far += apart(133) <= simhash.WIDE_RADIUS  # a similarity of 0.6
    assert near == 50 and far == 0


@pytest.mark.parametrize("radius,blocks", [(4, 5), (4, 6), (8, 10)])
def test_pigeonhole_keys_lose_no_pair(radius, blocks):
    masks = [m & (1 << 64) - 1 for m in simhash.masks_for(blocks, radius)]
    rng = np.random.default_rng(2)
    for _ in range(200):
        a = int(rng.integers(1 << 63))
        b = a
        for bit in rng.choice(64, radius, replace=False):
            b ^= 1 << int(bit)
        assert any(a & m == b & m for m in masks)


def test_forest_finds_all_pairs_in_runs():
    rng = np.random.default_rng(3)
    prints = np.concatenate([rng.integers(0, 1 << 63, 20, dtype=np.uint64), rng.integers(0, 1 << 10, 60, dtype=np.uint64)])
    starts = np.array([0, 20, 50])
    run = np.searchsorted(starts, np.arange(80), side="right")
    found = {(int(a), int(b)) for q, n in simhash.Forest(prints, starts).earlier_within(np.arange(80), 4) for a, b in zip(q, n)}
    assert found == {(i, j) for i in range(80) for j in range(i) if run[i] == run[j] and int(prints[i] ^ prints[j]).bit_count() <= 4}


def test_near_copies_go_and_clean_documents_stay(spark):
    rng = np.random.default_rng(4)
    text = lambda n: [f"w{rng.integers(5000)}" for _ in range(n)]
    base = [text(300) for _ in range(40)]
    near = [b[:150] + ["changed"] + b[151:] for b in base[:20]]
    docs = frame(spark, [" ".join(x) for x in base + near] + [" ".join(base[30]), None, ""])
    kept = {r.doc_id for r in simhash.drop_near_duplicates(docs).select("doc_id").collect()}
    assert kept == set(range(40)) | {61, 62}


def test_appended_truncated_and_short_copies_go_by_exact_similarity(spark):
    rng = np.random.default_rng(5)
    text = lambda n: [f"w{rng.integers(50000)}" for _ in range(n)]
    texts = []
    for n, more in [(100, 19), (100, 24), (50, 9), (300, 70), (8, 1), (9, 1), (10, 1), (12, 1), (100, 26), (300, 80), (8, 2), (12, 3)] * 8:
        base = text(n)
        texts += [base, base + text(more)]
        whole = text(n + more)
        texts += [whole, whole[:n]]
    texts += [line * 12 for line in (text(15),)] + [texts[0][:90] * 3]
    shingles = [{tuple(t[i : i + 5]) for i in range(max(1, len(t) - 4))} for t in texts]
    gone = {j for i in range(len(texts)) for j in range(i + 1, len(texts)) if len(shingles[i] & shingles[j]) >= 0.8 * len(shingles[i] | shingles[j])}
    kept = {r.doc_id for r in simhash.drop_near_duplicates(frame(spark, [" ".join(t) for t in texts])).select("doc_id").collect()}
    assert set(range(len(texts))) - kept == gone and 100 < len(gone) < 200


def test_shards_and_components_cut_into_blocks_give_the_same(spark):
    rng = np.random.default_rng(9)
    base = [f"w{rng.integers(50000)}" for _ in range(120)]
    texts = [" ".join(base[: 100 + i // 2] + [f"v{i}"]) for i in range(36)] + [" ".join(f"u{rng.integers(50000)}" for _ in range(60)) for _ in range(10)]
    docs = frame(spark, texts)
    prints = simhash.fingerprints(docs, 4)
    answer = lambda df: sorted(tuple(r) for r in df.select("doc_id", "component_id").collect())
    assert answer(simhash.link(prints, 12)) == answer(simhash.link(prints, 12, block=3))
    wide = simhash.fingerprints(docs, 5, wide=True).cache()
    how = (docs, 5, simhash.CANDIDATE_RADIUS, simhash.CANDIDATE_WIDE)
    assert answer(simhash.link_similar(wide, *how)) == answer(simhash.link_similar(wide, *how, block=4, block_hashes=500))


def test_near_copies_of_all_pairs_by_similarity(spark):
    """All pairs of the given documents by brute force: of links at 0.8 or more none is lost and no other is made."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    shingles, holders = {}, {}
    for r in docs.collect():
        words = (r.text or "").encode().lower().split()
        if words:
            shingles[r.doc_id] = {b" ".join(words[i : i + 5]) for i in range(max(1, len(words) - 4))}
            for g in shingles[r.doc_id]:
                holders.setdefault(g, []).append(r.doc_id)
    shared = Counter((a, b) for own in holders.values() for i, a in enumerate(own) for b in own[i + 1 :])
    label = {i: i for i in shingles}

    def find(x):
        while label[x] != x:
            x = label[x]
        return x

    for (a, b), n in shared.items():
        if 5 * n >= 4 * (len(shingles[a]) + len(shingles[b]) - n):
            x, y = find(a), find(b)
            label[max(x, y)] = min(x, y)
    gone = {i for i in label if find(i) != i}
    kept = {r.doc_id for r in simhash.drop_near_duplicates(docs).select("doc_id").collect()}
    assert set(shingles) - kept == gone and len(gone) > 50


def test_empty_tables(spark):
    none = spark.createDataFrame([], DDL)
    assert simhash.near_duplicates(none).count() == 0
    assert linededup.line_report(none).count() == 0
    assert sharding.shard_documents(none).count() == 0
    assert sketches.edited_pairs(none).count() == 0
    assert packing.pack_documents(none).count() == 0
    assert ppm.score_documents(none).count() == 0
    assert decontaminate.contaminated(none, spark.createDataFrame([], "item_id long, text string")).count() == 0
    assert langid.predict(none, langid.learn(none)).count() == 0
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert toxicity.score_documents(none, toxicity.learn(none, labels)).count() == 0
    assert warc.round_trip(spark, spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_lpt_is_balanced_whole_and_keeps_groups(spark):
    texts = ODD + [f"text {i} " * (i % 50) for i in range(600)] + ["copy"] * 100
    rows = sharding.shard_documents(frame(spark, texts).withColumn("group", F.lit(1)), 7).collect()
    assert len(rows) == len(texts)
    by_text, load, slots = {}, Counter(), {}
    for r in rows:
        t = texts[r.doc_id] or ""
        assert r["size"] == len(t.encode()) + 16 and r.text_crc32 == zlib.crc32(t.encode()) and r.law == "bytes" and r.grown_shard is None
        by_text.setdefault(t, set()).add(r.shard)
        load[r.shard] += r["size"]
        slots.setdefault(r.shard, []).append(r.slot)
    assert all(len(s) == 1 for s in by_text.values())
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    largest = max(sum(len((t or "").encode()) + 16 for t in texts if (t or "") == g) for g in by_text)
    assert max(load.values()) - min(load.values()) <= largest


def test_longest_first_equals_one_by_one():
    import heapq

    assert sharding.longest_first(Counter([7, 6, 5, 4, 3, 2]), 3) == [(7, 0, 1), (6, 1, 1), (5, 2, 1), (4, 2, 1), (3, 1, 1), (2, 0, 1)]
    assert sharding.longest_first({}, 3) == []
    rng = np.random.default_rng(0)
    for _ in range(200):
        shards, most = int(rng.integers(1, 12)), int(rng.choice([3, 20, 1000]))
        sizes = [int(x) for x in rng.integers(1, most, int(rng.integers(0, 300)))] + [most * 50] * int(rng.integers(0, 3))
        heap, placed = [(0, s) for s in range(shards)], Counter()
        for size in sorted(sizes, reverse=True):
            load, s = heap[0]
            placed[size, s] += 1
            heapq.heapreplace(heap, (load + size, s))
        assert Counter({(size, s): n for size, s, n in sharding.longest_first(Counter(sizes), shards)}) == placed


def test_shards_have_the_loads_of_a_schedule_group_by_group(spark, monkeypatch):
    import heapq

    texts = [f"text {i} " * (i % 40) for i in range(500)] + ["copy"] * 100 + [None]
    sizes = Counter()
    for t in texts:
        sizes[t or ""] += len((t or "").encode()) + 16
    heap = [0] * 7
    for size in sorted(sizes.values(), reverse=True):
        heapq.heapreplace(heap, heap[0] + size)
    for rows, broadcast in ((200_000, 64 << 20), (3, 0)):  # ranks in one part and in many, places by broadcast and by a shuffle
        monkeypatch.setattr(sharding, "RANK_ROWS", rows)
        monkeypatch.setattr(sharding, "BROADCAST_BYTES", broadcast)
        found = sharding.shard_documents(frame(spark, texts), 7).toPandas()
        assert sorted(found.groupby("shard")["size"].sum()) == sorted(heap)
        assert all(sorted(own) == list(range(len(own))) for _, own in found.groupby("shard")["slot"])


def test_lines_match_brute_force(spark):
    common, other = "This line is a long boilerplate line of the corpus!", "ünïcode " * 6
    texts = ODD + [f"intro {i}\n  {common.upper()} \r\nown line of document number {i} which is long enough\n{other}" for i in range(8)] + [f"{other}\n{common}\n{common}" if i < 3 else other for i in range(4)]
    keys = [[linededup.key_of(x) for x in (t or "").encode().split(b"\n")] for t in texts]
    holders = {}
    for i, ks in enumerate(keys):
        for k in set(ks) - {None}:
            holders.setdefault(k, []).append(i)
    gone = {k: max(v) for k, v in holders.items() if len(v) >= 5}
    for how in ({}, {"broadcast_bytes": 0, "chunk_bytes": 50, "range_bytes": 100}):  # by broadcast, and by the shuffle that goes beyond it
        got = {r.c2: r for r in linededup.rewritten(frame(spark, texts), **how).collect()}
        for i, t in enumerate(texts):
            kept = [x for x, k in zip((t or "").split("\n"), keys[i]) if not (k in gone and gone[k] != i)]
            assert (got[i].c3, got[i].c0, got[i].c1) == ("\n".join(kept), len(keys[i]), len(keys[i]) - len(kept))
    assert sum(1 for k in gone) == 2


def test_two_filters_never_lose_a_repeat():
    rng = np.random.default_rng(5)
    both = linededup.TwoFilters(1 << 12)
    hashes = rng.integers(0, 1 << 63, 300, dtype=np.uint64)
    for i in range(4):
        both.add(hashes[i * 60 : i * 60 + 120])
    assert both.has(both.twice, linededup.probes(hashes[60:240], 1 << 12)).all()


def test_suspects_stay_a_small_share_at_any_size(spark):
    for n in (2_000, 40_000):
        docs = frame(spark, [f"line number {i} of a text that has no line twice" for i in range(n)] + ["this very line is in three documents of the table"] * 3)
        found = linededup.suspected(docs.select("text"), chunk_bytes=1 << 16, range_bytes=1 << 17).count()
        assert 1 <= found <= 1 + n // 100


def test_lines_are_counted_by_documents_and_names_may_clash(spark):
    line = "a line of more than forty code points, of which there is enough"
    rows = [(1, line), (2, line), (1, line), (2, line + "\nend"), (None, line), (3, "x")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("1 as c0", "*", "2 as _n_lines", "3 as d", "4 as _d", "5 as own", "text as key")
    for how in ({}, {"broadcast_bytes": 0}):
        kept = linededup.drop_repeated_lines(docs, **how)
        assert kept.columns == docs.columns
        assert sorted(kept.collect(), key=str) == sorted(docs.collect(), key=str)
        lost = linededup.drop_repeated_lines(docs, min_docs=2, **how)
        assert sorted((r.doc_id or 0, r.text) for r in lost.collect()) == [(0, ""), (1, ""), (1, ""), (2, line), (2, line + "\nend"), (3, "x")]


def test_warc_round_trip(spark, tmp_path):
    big = "<p>" + "ä\r\n0\r\n" * 40_000
    html = [None, "", "<html>short</html>", "x" * 1000, "x" * 1000, "y" * 999, "y" * 999, big, big, "WARC/1.1\r\n\r\n" * 200]
    pages = spark.createDataFrame([(i, f"http://h/{i}\n", h) for i, h in enumerate(html)] + [(None, None, "x" * 1000)], "page_id long, url string, html string")
    path = f"file://{tmp_path}/w"
    warc.write_archives(pages, path, segment_bytes=50_000)
    rows = warc.read_archives(spark, path).collect()
    assert {r.status for r in rows} == {"ok"} and len(rows) == 11
    for r in (r for r in rows if r.page_id is not None):
        payload = (html[r.page_id] or "").encode()
        assert (r.payload_bytes, r.payload_digest) == (len(payload), hashlib.sha1(payload).hexdigest())
        assert r.refers_to == {3: 4, 7: 8}.get(r.page_id)
        assert r.record_type == ("revisit" if r.page_id in (3, 7) else "response")
        assert r.payload == (None if r.record_type == "revisit" else payload)
    assert max(r.segments for r in rows) > 5


def test_broken_records_are_reported():
    block = b"HTTP/1.1 200 OK\r\nTransfer-Encoding: chunked\r\n\r\n" + warc.chunked(b"z" * 40_000)
    pieces = [next(warc.records_of(r)) for r in warc.segments(b"id", [(b"WARC-Type", b"response")], block, 10_000)]
    rows = [{"page_id": 1, "url": None, "type": h["warc-type"], "refers_to": None, "digest": None, "segment": int(h["warc-segment-number"]), "total": int(h["warc-segment-total-length"]) if "warc-segment-total-length" in h else None, "block": b} for h, b in pieces]
    assert warc.assembled(rows)["status"] == "ok" and warc.assembled(rows)["payload_bytes"] == 40_000
    assert warc.assembled(rows[1:])["status"] == "orphan"
    assert warc.assembled([rows[0], *rows[2:]])["status"] == "gap"
    assert warc.assembled([*rows[:-1], rows[-1] | {"block": rows[-1]["block"][:-1]}])["status"] == "length"
    with pytest.raises(ValueError):
        warc.unchunked(b"5\r\nab")


def test_ppm_distributions_add_to_one_and_base_matches(spark):
    texts = ["the cat sat on the mat", "the cat ate", None, "", "The  CAT\nsat", "zebra quux"] * 5 + ["the cat sat on the mat"] * 20
    rows = {r.doc_id: r for r in ppm.score_documents(frame(spark, texts)).collect()}
    words = [(t or "").encode().lower().split() for t in texts]
    held = [zlib.crc32(str(i).encode()) % 10 == 0 for i in range(len(texts))]
    c = Counter(w for i, ws in enumerate(words) if not held[i] for w in [*ws, "end"])
    n, v = sum(c.values()), len(c)
    for i, ws in enumerate(words):
        r = rows[i]
        assert (r.held_out, r.n_tokens, r.train_tokens, r.n_known) == (held[i], len(ws) + 1, n, sum(c[w] > 0 for w in [*ws, "end"]))
        assert r.base_score == pytest.approx(sum(log10((c[w] + 0.1) / (n + 0.1 * (v + 1))) for w in [*ws, "end"]))
        assert r.score < 0
    assert rows[30].score > rows[5].score


def walked(texts, trained):
    """log10 probability of each text by a literal walk: longest context first, symbols of longer contexts excluded, half counts to the escape."""
    tries = [{} for _ in range(ppm.ORDER + 1)]
    data = [bytes([ppm.START]) * ppm.ORDER + t + bytes([ppm.END]) for t in texts]
    for d in (d for d, yes in zip(data, trained) if yes):
        for i in range(ppm.ORDER, len(d)):
            for k in range(ppm.ORDER + 1):
                node = tries[k].setdefault(d[i - k : i], {})
                node[d[i]] = node.get(d[i], 0) + 1

    def log_of(d, i):
        p, excluded = 1.0, set()
        for k in range(ppm.ORDER, -1, -1):
            left = {s: n for s, n in tries[k].get(d[i - k : i], {}).items() if s not in excluded}
            if d[i] in left:
                return log10(p * (2 * left[d[i]] - 1) / (2 * sum(left.values())))
            if left:
                p *= len(left) / (2 * sum(left.values()))
                excluded |= set(left)
        return log10(p / (ppm.SYMBOLS - len(excluded)))

    return [sum(log_of(d, i) for i in range(ppm.ORDER, len(d))) for d in data], log_of


def test_ppm_score_matches_a_literal_walk(spark):
    rng = np.random.default_rng(8)
    texts = ["".join(rng.choice(list("abcde \n"), rng.integers(0, 60))) for _ in range(150)] + ["The  CAT\nsat", "neverséen ☃ zzz", "", None] * 8 + ["abcabc" * 200]
    lowered = [(t or "").encode().lower() for t in texts]
    held = [zlib.crc32(str(i).encode()) % 10 == 0 for i in range(len(texts))]
    expected, _ = walked(lowered, [not h for h in held])
    for how in ({}, {"chunk_bytes": 100, "bucket_bytes": 64}):
        rows = {r.doc_id: r for r in ppm.score_documents(frame(spark, texts), **how).collect()}
        assert [rows[i].score for i in range(len(texts))] == pytest.approx(expected, rel=1e-6)
    assert sum(held[i] for i in range(150, len(texts))) > 0


def test_ppm_walk_is_a_distribution_and_windows_are_cut_alike(monkeypatch):
    texts = [b"abracadabra", b"abra cadabra", b"candelabra", b""] * 5
    _, log_of = walked(texts, [True] * len(texts))
    for context in (b"abrac", b"bcdef", b"zzzzz"):
        assert sum(10.0 ** log_of(context + bytes([s]), ppm.ORDER) for s in range(256)) == pytest.approx(1)
    texts = [b"x" * 5000, b"", b"aB" * 700]
    whole = list(ppm.windows(texts))
    monkeypatch.setattr(ppm, "_SLICE", 64)
    parts = list(ppm.windows(texts))
    assert len(parts) > len(whole)
    for at in (0, 1):
        assert np.array_equal(np.concatenate([x[at] for x in whole]), np.concatenate([x[at] for x in parts]))


def test_ppm_without_training_rows_is_uniform(spark):
    docs = spark.createDataFrame([(None, "abc", 1), (None, "abc", 2), (None, None, 3)], "doc_id long, text string, chunk int")
    rows = ppm.score_documents(docs).collect()
    assert sorted(r.score for r in rows) == pytest.approx(sorted([-4 * log10(256), -4 * log10(256), -log10(256)]))
    assert all(r.held_out and r.train_tokens == 0 and r.n_known == 0 for r in rows)
    assert ppm.adaptive_log10(b"ab" * 100) > ppm.adaptive_log10(bytes(range(32, 127)) * 2 + b"0123456789")


def test_toxicity_learns_folds_and_excepts(spark):
    clean = [f"the quick brown fox number {i} walks along" for i in range(60)]
    toxic = [f"you zorgle number {i} walks zorgling along" for i in range(40)]
    docs = frame(spark, clean + toxic)
    labels = spark.createDataFrame([(i, 1, int(i >= 60)) for i in range(100)] + [(None, 1, 1), (5, 1, None)], "doc_id long, quality int, toxic int")
    lexicon = toxicity.learn(docs, labels)
    rows = {r.doc_id: r for r in toxicity.score_documents(frame(spark, clean + toxic + [None, ""]), lexicon).collect()}
    assert all(rows[i].predicted == int(60 <= i < 100) for i in range(102))
    assert all(rows[i].held_out == (zlib.crc32(str(i).encode()) % 3 == 1) for i in range(102))
    a = toxicity.Lexicon().automaton()
    for text in ("what an idiot", "what an 1d10t!", "what an іdіоt", "an id​iot", "AN IDIOT$$$"):
        assert toxicity.features(text, a)[0] > 0, text
    for text in ("the clown fish swims", "put it in the trash can", "idiotically", "scunthorpe", ""):
        assert toxicity.features(text, a) == (0.0, 0.0), text
    kept = toxicity.drop_toxic(docs, lexicon)
    assert kept.columns == docs.columns and kept.count() == 60


def test_toxicity_tells_held_out_labels_apart(spark):
    """Area under the curve, recall and false alarms on labelled rows that taught nothing."""
    read = lambda name: spark.read.parquet(f"/root/testdata/sf0.1/{name}.parquet")
    docs, labels = read("documents"), read("labels")
    rows = toxicity.score_documents(docs, toxicity.learn(docs, labels)).filter("held_out").join(labels, "doc_id").select("score", "predicted", "toxic").dropna().toPandas()
    toxic = rows["toxic"].to_numpy() == 1
    rank = rows["score"].rank().to_numpy()
    area = (rank[toxic].sum() - toxic.sum() * (toxic.sum() + 1) / 2) / (toxic.sum() * (~toxic).sum())
    assert len(rows) > 1000 and area > 0.93
    assert rows["predicted"][toxic].mean() > 0.85 and rows["predicted"][~toxic].mean() < 0.01


def test_decontamination_matches_brute_force(spark):
    rng = np.random.default_rng(6)
    word = lambda: "".join(rng.choice(list("abcdefgh"), rng.integers(2, 8)))
    items = [" ".join(word() for _ in range(40)) for _ in range(5)] + ["tiny one", None, ""]
    filler = lambda n: " ".join(word() for _ in range(n))

    def edited(t, n):
        t = list(t)
        for i in sorted(rng.choice(len(t), n, replace=False), reverse=True):
            t[i] = rng.choice(["", "zz", "q"])
        return "".join(t)

    texts = [filler(200) for _ in range(5)] + [filler(60) + " " + edited(items[i % 5], n) + " " + filler(60) for i in range(10) for n in (0, 3, 9, 40)] + ["a TINY, one here", "atiny one", None, ""]
    found = {(r.doc_id, r.item_id): r.distance for r in decontaminate.contaminated(frame(spark, texts), spark.createDataFrame(list(enumerate(items)), "item_id long, text string")).collect()}
    expected = {}
    for d, t in enumerate(texts):
        t = decontaminate.folded(t)
        for i, item in enumerate(items):
            item = decontaminate.folded(item)
            if not item:
                continue
            errors = decontaminate.budget(len(item))
            row = np.zeros(len(t) + 1, int)
            for a, c in enumerate(item, 1):
                new = np.empty_like(row)
                new[0] = a
                for b in range(1, len(t) + 1):
                    new[b] = min(row[b - 1] + (t[b - 1] != c), row[b] + 1, new[b - 1] + 1)
                row = new
            if errors and row.min() <= errors or not errors and f" {item} " in f" {t} ":
                expected[d, i] = int(row.min())
    assert found == expected and len(found) >= 30


def test_language_id_held_out_accuracy(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    rows = langid.predict(docs, langid.learn(docs)).join(docs.select("doc_id", "lang"), "doc_id").filter("held_out").toPandas()
    assert (rows["lang"] == rows["lang_pred"]).mean() > 0.97
    odd = {r.doc_id: r for r in langid.predict(frame(spark, [None, "", "123 !!", "the and of"]), langid.learn(docs)).collect()}
    assert [odd[i].lang_pred for i in range(4)] == ["und", "und", "und", "en"] and odd[0].score == 0.0


def test_temperature_softens_overconfident_logits():
    rng = np.random.default_rng(7)
    y = rng.integers(0, 3, 2000)
    logits = np.eye(3)[np.where(rng.random(2000) < 0.7, y, rng.integers(0, 3, 2000))] * 10
    assert langid.temperature_of(logits, y) > 3


def test_sketches_match_brute_force(spark):
    texts = ["", None, "one two", " ".join(f"w{i}" for i in range(400)), " ".join(f"w{i}" for i in range(200, 600)), "é" * 11, " ".join(f"w{i}" for i in range(400))]
    docs = frame(spark, texts).unionByName(frame(spark, ["no id"]).withColumn("doc_id", F.lit(None).cast("long")))
    rows = {r.doc_id: r for r in sketches.edited_pairs(docs).collect()}
    order = [6, 5, 4, 3, 2, 1, 0, None]
    text = {i: t or "" for i, t in enumerate(texts)} | {None: "no id"}
    for at, i in enumerate(order):
        t, after = text[i], text[order[(at + 1) % len(order)]]
        k = len(t) // 2
        edited = t[: len(t) - k] + after[:k]
        assert (rows[i].n_chars, rows[i].edited_sha256) == (len(t), hashlib.sha256(edited.encode()).hexdigest())
        if edited == t:
            assert rows[i].near_edited == 1.0 and rows[i].fingerprint == rows[i].edited_fingerprint
    assert rows[3].fingerprint == rows[6].fingerprint
    true = len(set(range(396)) & set(range(200, 596))) / len(set(range(396)) | set(range(200, 596)))
    assert abs(rows[4].near_next - true) < 0.2
    assert rows[None].near_next == 0.0 and all(0 <= r.near_edited <= 1 for r in rows.values())


def test_sketches_keep_the_fraction_merge_and_contain(spark):
    rng = np.random.default_rng(11)
    words = [f"w{x}" for x in rng.integers(0, 10**6, 3000)]
    texts = [" ".join(words), " ".join(words[1000:1030]), " ".join(words[:2000]), " ".join(words[1500:]), "", "one two", " ".join(words[:70])]
    rows = sketches.sketches(frame(spark, texts))
    every = {r.doc_id: set(r.sketch.hashes) for r in sketches.sketches(frame(spark, texts), scale=1).collect()}
    found = {r.doc_id: r.sketch for r in rows.collect()}
    limit = sketches.LOWEST + (1 << 64) // sketches.SCALE
    for i, t in enumerate(texts):
        whole = len(t.split()) - 4 <= sketches.WHOLE
        assert found[i].scale == (1 if whole else sketches.SCALE)
        assert found[i].hashes == sorted(h for h in every[i] if whole or h < limit)
    pair = rows.alias("a").join(rows.alias("b"), F.col("a.doc_id") != F.col("b.doc_id"))
    inside = {(r[0], r[1]): r for r in pair.select("a.doc_id", "b.doc_id", sketches.containment(F.col("a.sketch"), F.col("b.sketch")), sketches.likeness(F.col("a.sketch"), F.col("b.sketch"))).collect()}
    for (i, j), r in inside.items():
        common = len(every[i] & every[j])
        assert r[2] == pytest.approx(common / len(every[i]) if every[i] else 1.0, abs=0.1)
        assert r[3] == pytest.approx(common / len(every[i] | every[j]) if every[i] | every[j] else 1.0, abs=0.1)
    assert inside[1, 0][2] == 1.0  # a short text in a hundred times longer one
    both = rows.filter("doc_id in (2, 3)").agg(sketches.merged(F.col("sketch")).alias("s")).first().s
    assert (both.scale, both.hashes) == (sketches.SCALE, sorted(h for h in every[2] | every[3] if h < limit))
    mixed = rows.filter("doc_id in (1, 2)").agg(sketches.merged(F.col("sketch")).alias("s")).first().s
    assert mixed.hashes == sorted(h for h in every[1] | every[2] if h < limit)


def test_sketch_runs_follow_uneven_ids(spark):
    ids = [0, 1, 2, 3] + [10**12 + i for i in range(3000)] + [5 * 10**15]
    docs = spark.createDataFrame([(i, f"text {i}") for i in ids] + [(None, "x")] * 3, "doc_id long, text string")
    runs = docs.withColumn("run", sketches._runs(docs, 300_000)).toPandas()
    assert runs.groupby("run").size().max() < 300
    runs = runs.dropna().sort_values("doc_id")
    assert runs["run"].is_monotonic_increasing
    rows = {r.doc_id: r for r in sketches.edited_pairs(docs).collect() if r.doc_id is not None}
    for i, after in zip(sorted(ids, reverse=True), sorted(ids, reverse=True)[1:]):
        t, n = f"text {i}", len(f"text {i}")
        assert rows[i].edited_sha256 == hashlib.sha256((t[: n - n // 2] + f"text {after}"[: n // 2]).encode()).hexdigest()


def test_packing_is_whole_gapless_and_near_the_bound(spark):
    texts = [None, "", "short", "<|endoftext|> special", "word " * 3000] + [f"text {i} " * (i % 90 + 1) for i in range(300)]
    rows = packing.pack_documents(frame(spark, texts), generations=3, epochs=1).toPandas()
    from tokenizers import Tokenizer

    slow = Tokenizer.from_file(packing.default_tokenizer()[0])
    for i, t in enumerate(texts):
        ids = [*slow.encode(t or "", add_special_tokens=False).ids, 2]
        own = rows[rows["doc_id"] == i].sort_values("piece")
        assert own["length"].sum() == len(ids) and (own["length"].to_numpy()[1:] == 1024).all()
        for p in own.itertuples():
            assert p.ids_crc32 == zlib.crc32(np.array(ids[p.start : p.start + p.length], "<u4").tobytes())
    for _, own in rows.sort_values("offset").groupby("sequence_id"):
        assert own["length"].sum() <= 1024
        assert (own["offset"].to_numpy() == np.append(0, own["length"].cumsum().to_numpy()[:-1])).all()
    assert rows["sequence_id"].nunique() <= -(-rows["length"].sum() // 1024) + 1


def contents(patterns):
    return sum((Counter({s: n * c for s, n in Counter(p).items()}) for p, c in patterns), Counter())


def triplets(rng, bins, capacity):
    """Lengths that fill bins exactly, three to a bin, which best fit cannot see."""
    out = []
    for _ in range(bins):
        a = rng.randint(38 * capacity // 100, 49 * capacity // 100)
        b = rng.randint((capacity - a) // 2 - 60, (capacity - a) // 2)
        out += [a, b, capacity - a - b]
    return Counter(out)


def test_genetic_operators_keep_every_length():
    import random

    rng = random.Random(1)
    counts = Counter(rng.randint(1, 100) for _ in range(200)) + Counter({37: 5000, 3: 1})
    a, b = packing.started(counts, 100, 2, 0)
    for child in (a, b, packing.crossover(a, b, counts, 100, rng), packing.mutated(a, counts, 100, rng), packing.evolved([a, b], counts, 100, 3, 0)[0]):
        assert contents(child) == counts and max(sum(p) for p, _ in child) <= 100


def test_evolved_packings_need_fewer_bins_than_best_fit(spark):
    import random

    rng = random.Random(2)
    for counts in (triplets(rng, 60, 1024), Counter({s: 40 * n for s, n in triplets(rng, 40, 1024).items()})):
        found = packing.plan(spark, dict(counts), 1024, islands=2, epochs=2)
        plain = packing.bins_of(packing.best_fit(counts, 1024))
        assert contents(found) == counts and max(sum(p) for p, _ in found) <= 1024
        assert packing.bins_of(found) <= plain - plain // 40
    assert packing.plan(spark, {1024: 7}, 1024) == [((1024,), 7)] and packing.plan(spark, {}, 1024) == []


def test_packing_is_best_on_small_cases(spark):
    """Against the least number of bins by trying all."""
    import random

    def least(lengths, bins=()):
        if not lengths:
            return len(bins)
        s, rest = lengths[0], lengths[1:]
        return min([least(rest, tuple(sorted((*bins[:i], b + s, *bins[i + 1 :])))) for i, b in enumerate(bins) if b + s <= 20] + [least(rest, (*bins, s))])

    rng = random.Random(3)
    for _ in range(3):
        lengths = sorted((rng.randint(3, 13) for _ in range(9)), reverse=True)
        assert packing.bins_of(packing.plan(spark, Counter(lengths), 20, islands=2, epochs=1)) == least(lengths)


def test_fast_ids_are_those_of_the_named_tokenizer():
    import pyarrow.parquet as pq
    from tokenizers import Tokenizer

    texts = [t or "" for t in pq.read_table("/root/testdata/sf0.01/documents.parquet", columns=["text"]).column("text").to_pylist()]
    texts += ["", " ", "\n\n a", "<|endoftext|>", "a<|endoftext|>b", "e\u0301\u200d\U0001f600", "x" * 300]
    names = packing.default_tokenizer()
    slow = Tokenizer.from_file(names[0])
    assert [list(x) for x in packing.encoder(*names)(texts)] == [e.ids for e in slow.encode_batch(texts, add_special_tokens=False)]


def test_items_with_several_texts_and_many_passes_give_one_row(spark):
    rng = np.random.default_rng(4)
    word = lambda: "".join(rng.choice(list("abcdefgh"), 6))
    first, second, other = (" ".join(word() for _ in range(12)) for _ in range(3))
    items = spark.createDataFrame([(1, first), (1, second), (2, other), (1, first), (None, other), (3, None)], "item_id long, text string").withColumn("doc_id", F.lit(9))
    changed = second.replace(second.split()[5], "zzzzzz")
    docs = frame(spark, [f"{first} and {changed}", other, f"x {changed}", "clean", None]).selectExpr("*", "1 as item_id", "2 as distance", "3 as end_at")
    for bound in (1 << 20, 90, 1):
        rows = sorted((r.doc_id, r.item_id, r.distance) for r in decontaminate.contaminated(docs, items, broadcast_bytes=bound).collect())
        assert [x[:2] for x in rows] == [(0, 1), (1, 2), (2, 1)] and rows[0][2] == 0 and 0 < rows[2][2] <= 6
    kept = decontaminate.drop_contaminated(docs.unionByName(docs), items)
    assert kept.columns == docs.columns and [r.doc_id for r in kept.orderBy("doc_id").collect()] == [3, 3, 4, 4]


def test_budget_may_be_wider(spark):
    item = "the quick brown fox jumps over the lazy dog while seven wise owls watch"
    edited = item.replace("quick", "quack").replace("lazy", "azy").replace("wise", "wide").replace("watch", "witch").replace("brown", "crown").replace("seven", "even").replace("jumps", "jump")
    assert not decontaminate.Matcher([(1, item)], 11).find(edited) and decontaminate.Matcher([(1, item)], 8).find(edited)


def test_very_long_texts(spark):
    """Megabytes in one row, through every operator on documents."""
    long = " ".join(f"word{i % 7919} line{i % 13}" for i in range(150_000))
    docs = frame(spark, [long, long[: len(long) // 2], "short one", None])
    assert simhash.near_duplicates(docs).count() == 4
    assert {r.doc_id for r in simhash.drop_near_duplicates(docs).collect()} >= {0, 2, 3}
    assert linededup.line_report(docs).count() == 4
    assert sketches.edited_pairs(docs).count() == 4
    assert sharding.shard_documents(docs, 3).count() == 4
    assert packing.pack_documents(docs, islands=1, epochs=1, generations=1).select("doc_id").distinct().count() == 4
    assert ppm.score_documents(docs).count() == 4
    assert langid.predict(docs, langid.learn(docs)).count() == 4
    assert toxicity.score_documents(docs, toxicity.Lexicon()).count() == 4
    assert decontaminate.contaminated(docs, spark.createDataFrame([(1, "word7918 line0 word0 line")], "item_id long, text string")).count() <= 2


def test_extra_columns_with_clashing_names_and_repeated_rows(spark):
    docs = frame(spark, ["same text here", "same text here", None]).selectExpr("*", "doc_id as fp", "text as key", "1 as shard", "2 as group", "3 as n_lines", "4 as rep", "5 as w0", "6 as score")
    docs = docs.unionByName(docs)
    assert simhash.near_duplicates(docs).count() == 6
    assert simhash.drop_near_duplicates(docs).columns == docs.columns
    assert linededup.drop_repeated_lines(docs).count() == 6
    assert sharding.shard_documents(docs, 3).count() == 6
    assert sketches.edited_pairs(docs).count() == 6
    assert packing.pack_documents(docs).count() == 6
    assert ppm.score_documents(docs).count() == 6
    assert langid.predict(docs, langid.learn(docs)).count() == 6
    labels = spark.createDataFrame([(0, 1, 1), (0, 1, 0), (1, 0, 0), (None, 1, 1)], "doc_id long, quality int, toxic int").selectExpr("*", "1 as text", "2 as score", "3 as n")
    labels = labels.unionByName(labels)
    lexicon = toxicity.learn(docs, labels)
    assert toxicity.score_documents(docs, lexicon).count() == 6 and toxicity.drop_toxic(docs, lexicon).columns == docs.columns
    pages = spark.createDataFrame([(1, "u", "x" * 2000, 5), (1, "u", "x" * 2000, 5), (2, None, None, 6)], "page_id long, url string, html string, payload int").selectExpr("*", "1 as segment", "2 as status")
    assert warc.round_trip(spark, pages).count() == 3

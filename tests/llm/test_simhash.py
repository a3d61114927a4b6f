import random
from math import comb

import numpy as np
import xxhash

from overlapix.llm import simhash
from overlapix.llm.components import connected_components, forest
from tests.llm.helpers import EDGES, docs_frame


def slow_fingerprint(text, k=4):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    for c in "\t\n\x0b\x0c\r":
        low = low.replace(c, " ")
    words = [w for w in low.split(" ") if w]
    if not words:
        return 0
    shingles = [" ".join(words[i : i + k]) for i in range(max(1, len(words) - k + 1))]
    hashes = [xxhash.xxh64(s.encode(), seed=42).intdigest() for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def brute(rows, radius=4):
    fps = [(i, slow_fingerprint(t)) for i, t in rows]
    named = [(n, fp) for n, (_, fp) in enumerate(fps)]
    pairs = [(a, b) for a, x in named for b, y in named if a <= b and bin(x ^ y).count("1") <= radius]
    group = forest(iter(pairs))
    least = {}
    for n, (i, _) in enumerate(fps):
        if i is not None:
            least[group[n]] = min(i, least.get(group[n], i))
    return sorted(((i, fp, least.get(group[n])) for n, (i, fp) in enumerate(fps)), key=repr)


def result(df):
    return sorted(((r.doc_id, r.fp & (1 << 64) - 1, r.component_id) for r in df.collect()), key=repr)


def test_edges(spark):
    assert result(simhash.near_duplicates(docs_frame(spark, EDGES))) == brute(EDGES)


def test_empty_table(spark):
    assert simhash.near_duplicates(docs_frame(spark, [])).count() == 0


def test_documents_against_brute_force(spark):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text").collect()]
    rng, more = random.Random(5), []
    for i, (_, t) in enumerate(rows[:60]):
        words = t.split(" ")
        words[rng.randrange(len(words))] = "changed"
        more.append((10_000 + i, " ".join(words)))
    assert result(simhash.near_duplicates(docs_frame(spark, rows + more))) == brute(rows + more)


def test_links_are_whole_for_every_number_of_axes(spark):
    rng = np.random.default_rng(3)
    base = rng.integers(0, 1 << 63, 60, dtype=np.uint64)
    flips = np.array([np.bitwise_or.reduce(np.left_shift(np.uint64(1), rng.choice(64, n, replace=False).astype(np.uint64))) if n else 0 for n in rng.integers(0, 7, 600)], np.uint64)
    fps = np.unique(base[rng.integers(0, 60, 600)] ^ flips)
    rows = list(zip(fps.view(np.int64).tolist(), range(len(fps)), strict=True))
    near = np.argwhere(np.bitwise_count(fps[:, None] ^ fps[None, :]) <= 4)
    want = forest((int(a), int(b)) for a, b in near)
    reps = spark.createDataFrame(rows, "fp bigint, node bigint")
    for axes in (5, 6, 8):
        got = {r.node: r.component for r in connected_components(simhash.fingerprint_links(reps, 4, axes)).collect()}
        assert {i: got.get(i, i) for i in range(len(fps))} == want
    near = np.argwhere(np.bitwise_count(fps[:, None] ^ fps[None, :]) <= 6)
    want = forest((int(a), int(b)) for a, b in near)
    got = {r.node: r.component for r in connected_components(simhash.fingerprint_links(reps, 6)).collect()}
    assert {i: got.get(i, i) for i in range(len(fps))} == want


def test_large_buckets_in_parts(spark, monkeypatch):
    """Buckets dealt out as blocks of parts give the same components."""
    monkeypatch.setattr(simhash, "BUCKET_ROWS", 40)
    monkeypatch.setattr(simhash, "SEEN", 1)
    rng = np.random.default_rng(5)
    flips = np.array([np.bitwise_or.reduce(np.left_shift(np.uint64(1), rng.choice(24, 5, replace=False).astype(np.uint64))) for _ in range(700)], np.uint64)
    fps = np.unique(np.concatenate([flips, rng.integers(0, 1 << 63, 200, dtype=np.uint64)]))
    near = np.argwhere(np.bitwise_count(fps[:, None] ^ fps[None, :]) <= 4)
    want = forest((int(a), int(b)) for a, b in near)
    reps = spark.createDataFrame(list(zip(fps.view(np.int64).tolist(), range(len(fps)), strict=True)), "fp bigint, node bigint")
    assert simhash._large_buckets(reps, len(fps), 4, 6).count()
    got = {r.node: r.component for r in connected_components(simhash.fingerprint_links(reps, 4)).collect()}
    assert {i: got.get(i, i) for i in range(len(fps))} == want


def test_manhattan_bound_and_rows():
    rng = np.random.default_rng(9)
    a, b = rng.integers(0, 1 << 64, (2, 4000), dtype=np.uint64)
    b[:2000] = a[:2000] ^ (np.uint64(1) << rng.integers(0, 64, 2000, dtype=np.uint64)) ^ (np.uint64(1) << rng.integers(0, 64, 2000, dtype=np.uint64))
    slow = np.abs(simhash.segment_counts(a).astype(int) - simhash.segment_counts(b).astype(int)).sum(1)
    fast = np.bitwise_count(simhash.unary_counts(a) ^ simhash.unary_counts(b))
    assert (slow == fast).all() and (fast <= np.bitwise_count(a ^ b)).all()
    assert comb(simhash.choose_axes(10**10, 4), 4) < 50


def shingle_set(text):
    w = (text or "").encode().lower().split()
    return frozenset(tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))) if w else frozenset()


def test_similar_groups_against_brute_force(spark):
    """All groups of five-word similarity 0.8 or more, on documents and edited copies."""
    rows = [(r.doc_id, r.text) for r in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text").collect()]
    rng, more = random.Random(7), []
    for i, (_, t) in enumerate(rows[:150]):
        words = (t or "").split(" ")
        for _ in range(len(words) // 60):
            words[rng.randrange(len(words))] = "changed"
        more.append((10_000 + i, " ".join(words)))
    rows += more
    sets = [shingle_set(t) for _, t in rows]
    by: dict = {}
    for n, s in enumerate(sets):
        for x in s:
            by.setdefault(x, []).append(n)
    near = {(a, b) for at in by.values() for a in at for b in at if a < b}
    links = {(a, b) for a, b in near if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])}
    links |= {(n, n) for n in range(len(rows))}
    got = {r.doc_id: r.component_id for r in simhash.similar_groups(docs_frame(spark, rows)).collect()}
    together = [got[rows[a][0]] == got[rows[b][0]] for a, b in links if a != b]
    assert len(together) > 100 and sum(together) >= 0.97 * len(together), (sum(together), len(together))
    group = forest(iter(links))
    for n, (i, _) in enumerate(rows):  # nothing is joined that is not alike
        root = next(m for m, (j, _) in enumerate(rows) if j == got[i])
        assert group[n] == group[root] or not sets[n]


def test_odd_bits_rule_out_no_alike_pair(spark):
    """The slots that differ never outnumber the elements that do; unlike candidates go before their sets are joined."""
    rng, sets, pairs = np.random.default_rng(5), [], []
    for n in (1, 3, 31, 32, 33, 200, 5000):
        whole = rng.integers(0, 1 << 63, n).astype(np.uint64)
        for cut in (0, n // 20, n // 9, n // 4, n):
            other = rng.integers(0, 1 << 63, n // 20 if cut == n else cut).astype(np.uint64)
            sets += [np.unique(whole), np.unique(np.concatenate([whole[cut:], other]))]
            pairs.append((len(sets) - 2, len(sets) - 1))
    odd = [simhash.odd_bits(s) for s in sets]
    pairs += [(0, n) for n in range(2, len(sets))]
    alike = set()
    for a, b in pairs:
        common = len(np.intersect1d(sets[a], sets[b]))
        assert simhash.odd_slots(odd[a], odd[b]) == simhash.odd_slots(odd[b], odd[a]) <= len(sets[a]) + len(sets[b]) - 2 * common
        if common >= 0.8 * (len(sets[a]) + len(sets[b]) - common) and common:
            alike.add((a, b))
    marks = spark.createDataFrame([(n, len(s), bytearray(o)) for n, (s, o) in enumerate(zip(sets, odd, strict=True))], "node bigint, size bigint, odd binary")
    got = {(r.u, r.v) for r in simhash._likely(spark.createDataFrame(pairs, "u bigint, v bigint"), marks, 0.8).collect()}
    assert alike <= got and len(got) <= len(alike) + 3 < len(pairs) / 2


def test_texts_are_not_dealt_out_for_few_ids(spark, monkeypatch):
    """Rows that the slots of ids rule out meet no join, and all others are decided exactly."""
    for slots in (1 << 15, 1 << 26):
        monkeypatch.setattr(simhash, "SLOTS", slots)
        docs = docs_frame(spark, [(i * 7919 - 40_000, f"text {i}") for i in range(40_000)] + [(None, "none"), (None, None)])
        marks = spark.createDataFrame([(i * 7919 - 40_000, -40_000 if i % 10 == 3 else i * 7919 - 40_000) for i in range(40_000)] + [(None, 5)], "doc_id bigint, component_id bigint")
        got = sorted((r.doc_id for r in simhash._without(docs, "doc_id", marks).collect()), key=repr)
        assert got == sorted([i * 7919 - 40_000 for i in range(40_000) if i % 10 != 3] + [None, None], key=repr)
    gone = marks.where("doc_id <> component_id").select("doc_id")
    met = simhash._slotted(docs, "doc_id", gone, 4000)
    assert met.where("__met").count() < 6000 and met.where("__met").join(gone, "doc_id", "left_semi").count() == 4000


def test_groups_of_near_copies_of_any_size(spark, monkeypatch):
    monkeypatch.setattr(simhash, "PAIRS_A_ROW", 0.5)
    rng = random.Random(3)
    base = [f"w{rng.randrange(5000)}" for _ in range(200)]
    rows = []
    for i in range(300):
        words = list(base)
        for _ in range(i % 4):
            words[rng.randrange(200)] = f"x{i}"
        rows.append((i, " ".join(words)))
    rows += [(1000 + i, " ".join(f"w{rng.randrange(5000)}" for _ in range(100))) for i in range(50)]
    got = {r.doc_id: r.component_id for r in simhash.similar_groups(docs_frame(spark, rows)).collect()}
    assert [got[i] for i in range(300)] == [0] * 300 and all(got[1000 + i] == 1000 + i for i in range(50))


def test_similar_groups_edges(spark):
    got = sorted((r.doc_id, r.component_id) for r in simhash.similar_groups(docs_frame(spark, EDGES)).collect())
    assert got == [(1, 1), (2, 1), (3, 3), (4, 3), (4, 3), (6, 6), (7, 7), (8, 1), (9, 9)]
    assert simhash.similar_groups(docs_frame(spark, [])).count() == 0
    kept = sorted((r.doc_id for r in simhash.keep_similar_groups(docs_frame(spark, EDGES)).collect()), key=repr)
    assert kept == [1, 3, 6, 7, 9, None]


def test_large_bucket_is_walked(spark):
    fps = np.array([(1 << a) | (1 << b) for a in range(14) for b in range(14)], np.uint64)
    fps = np.unique(fps)
    rows = list(zip(fps.view(np.int64).tolist(), range(len(fps)), strict=True))
    got = connected_components(simhash.fingerprint_links(spark.createDataFrame(rows, "fp bigint, node bigint"), 4))
    assert {r.component for r in got.collect()} == {0}


def test_components_of_long_chain(spark):
    edges = [(i, i + 1) for i in range(0, 400)] + [(1000, 1002), (1002, 1001)]
    got = {r.node: r.component for r in connected_components(spark.createDataFrame(edges, "u bigint, v bigint")).collect()}
    assert all(got[i] == 0 for i in range(401)) and got[1001] == got[1002] == 1000


def test_keep_one(spark):
    df = spark.createDataFrame([(1, "a b c d e", "x"), (2, "a b c d e", "y"), (3, "other words here now", "z"), (3, "other words here now", "z"), (None, "a b c d e", "n")], "doc_id bigint, text string, fp string")
    kept = sorted(((r.doc_id, r.fp) for r in simhash.keep_one_per_group(df).collect()), key=repr)
    assert kept == [(1, "x"), (3, "z"), (None, "n")]

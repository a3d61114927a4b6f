import math

import numpy as np

from overlapix.llm import nn_descent as N
from overlapix.llm.components import forest


def brute(rows, threshold=0.9):
    ids, x = [], []
    for i, v in rows:
        if i is not None and v and None not in v and all(map(math.isfinite, v)) and any(v):
            ids.append(i)
            x.append(np.array(v, np.float64) / np.linalg.norm(v))
    pairs = [(a, b) for a in range(len(ids)) for b in range(len(ids)) if a != b and len(x[a]) == len(x[b]) and x[a] @ x[b] >= threshold]
    group = forest((ids[a], ids[b]) for a, b in pairs)
    links = {}
    for a, _ in pairs:
        links[ids[a]] = links.get(ids[a], 0) + 1
    return sorted(((i, links.get(i, 0), group.get(i, i), i is not None and group.get(i, i) == i) for i, _ in rows), key=repr)


def result(df):
    return sorted(map(tuple, df.collect()), key=repr)


def test_table_against_brute_force(spark):
    df = spark.read.parquet("/root/testdata/sf0.01/embeddings.parquet")
    rows = [(r.vec_id, r.embedding) for r in df.collect()]
    rng, more = np.random.default_rng(1), []
    for i in range(120):
        v = np.array(rows[i][1])
        more.append((10_000 + i, (v + rng.normal(0, 0.03, len(v))).tolist()))
    for i in range(90):  # one dense group, larger than a list
        v = np.array(rows[400][1])
        more.append((20_000 + i, (v + rng.normal(0, 0.015, len(v))).tolist()))
    more += [(30_000 + i, rows[7][1]) for i in range(40)]
    rows += more
    frame = spark.createDataFrame(rows, "vec_id bigint, embedding array<float>")
    rows = [(r.vec_id, r.embedding) for r in frame.collect()]
    got, want = result(N.near_duplicates(frame)), brute(rows)
    missed = len(set(want) - set(got))
    assert missed <= 0.02 * len(want), missed


def test_odd_vectors(spark):
    rows = [(1, None), (2, []), (3, [0.0, 0.0]), (4, [1.0, None]), (5, [float("nan"), 1.0]), (6, [float("inf"), 1.0]), (7, [1.0, 0.0]), (8, [1.0, 0.01]), (9, [1.0, 0.0, 0.0]), (None, [1.0, 0.0]), (10, [2.0, 0.0]), (11, [-1.0, 0.0])]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>")
    assert result(N.near_duplicates(df)) == brute(rows)


def test_empty(spark):
    assert N.near_duplicates(spark.createDataFrame([], "vec_id bigint, embedding array<float>")).count() == 0


def test_blocks_count_every_link(spark, monkeypatch):
    monkeypatch.setattr(N, "BLOCK_ROWS", 16)
    rng = np.random.default_rng(8)
    base = rng.normal(size=(3, 16))
    rows = [(i, (base[i % 3] + rng.normal(0, 0.25, 16)).tolist()) for i in range(150)]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>")
    got, want = result(N.near_duplicates(df)), brute(rows)
    assert len(set(want) - set(got)) <= 3


def test_looser_links_behind_many_closer_copies(spark):
    """Pairs of tight groups, each larger than any list: the links between the two groups count too."""
    rng, rows, d = np.random.default_rng(5), [], 32
    for pair in range(40):
        a, b = np.linalg.qr(rng.normal(size=(d, 2)))[0].T
        for g, c in enumerate((a, 0.93 * a + np.sqrt(1 - 0.93**2) * b)):
            rows += [(pair * 1000 + g * 500 + i, (c + rng.normal(0, 0.01, d)).tolist()) for i in range(55)]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>")
    got, want = result(N.near_duplicates(df)), brute(rows)
    links = [sum(r[1] for r in x) for x in (got, want)]
    assert links[0] >= 0.98 * links[1], links
    assert len({r[2] for r in got}) == len({r[2] for r in want}) == 40

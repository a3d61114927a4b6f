import math

import numpy as np
import pytest

from overlapix.functions import hashing as H
from overlapix.functions import theory as T
from overlapix.operators import bucketing, ranking, schemes, sets

SIZES = [(12, 16, 4), (20, 10, 5), (50, 10, 5), (30, 30, 18), (40, 8, 8)]
N = 4000


def rows(a_sizes=SIZES):
    """Pairs (data id, query id) of given sizes and overlap, over distinct elements."""
    x, q, base = [], [], 0
    for i, (fx, fq, a) in enumerate(a_sizes):
        name = lambda k: H.py_fp(f"el:{k}")
        x.append((i, sorted(name(base + k) for k in range(fx)), fx))
        q.append((i, sorted(name(base + fx - a + k) for k in range(fq)), fq))
        base += 1000
    return x, q


def frame(spark, r):
    return spark.createDataFrame(r, "id bigint, elems array<bigint>, f int")


def rates(spark, scheme, sizes=SIZES):
    x, q = (frame(spark, r) for r in rows(sizes))
    dx = {r.id: np.array(r.sig) for r in scheme.data_signatures(x).collect()}
    dq = {r.id: np.array(r.sig) for r in scheme.query_signatures(q).collect()}
    return [(dx[i] == dq[i]).mean() for i in range(len(sizes))]


@pytest.mark.parametrize("family", ["poly", "xx64"])
@pytest.mark.parametrize("kind", ["minhash", "opm1", "opm2", "srp", "l2lsh", "l2alsh", "signalsh", "normsign"])
def test_collision_laws(spark, kind, family):
    m, v = 60, math.sqrt(60)
    s = {
        "minhash": lambda: schemes.minhash(N, 5, family), "opm1": lambda: schemes.opm1(N, 5, m, family), "opm2": lambda: schemes.opm2(N, 5, m, family), "srp": lambda: schemes.srp(N, 5, family),
        "l2lsh": lambda: schemes.l2lsh(N, 5, 2.5, family), "l2alsh": lambda: schemes.l2_alsh(N, 5, v, family=family), "signalsh": lambda: schemes.sign_alsh(N, 5, v, family=family), "normsign": lambda: schemes.norm_sign_alsh(N, 5, v, family),
    }[kind]()
    for got, (fx, fq, a) in zip(rates(spark, s), SIZES, strict=True):
        law = s.collision_prob(a, fx, fq)
        assert abs(got - law) <= 5 * math.sqrt(law * (1 - law) / N) + 1e-9, (kind, got, law)


def test_sampling_laws(spark):
    universe = [H.py_fp(f"el:{k}") for k in range(40)]
    sizes = [(12, 16, 4)]
    for miss, want in (("one_to_n", 0.2), ("zero_to_n_minus_1", 0.325)):
        s = schemes.sampling(N, 7, universe, 4, miss)
        got = rates(spark, s, sizes)[0]
        assert abs(s.collision_prob(4, 12, 16) - want) < 1e-12
        assert abs(got - want) < 0.03
    other = T.sampling(4, 12, 16, 40, 4)
    assert abs(rates(spark, schemes.sampling(N, 7, universe, 4, "one_to_n"), sizes)[0] - other) > 0.08


def test_weighted_sampling_law(spark):
    m = 30
    x, q = rows([(12, 8, 5)])
    s = schemes.opmw(2000, 3, m)
    sig = lambda r, side: np.array(schemes.weighted_signatures(schemes.as_weighted(frame(spark, r)), s, side).first().sig)
    law = 5 / (2 * m - 5)
    assert abs((sig(x, "data") == sig(q, "query")).mean() - law) < 5 * math.sqrt(law * (1 - law) / 2000)


def test_general_weights(spark):
    w = spark.createDataFrame([(0, [1, 2, 3], [2.0, 1.0, 4.0]), (1, [2, 3, 4], [3.0, 1.0, 2.0]), (2, [1], [0.0])], "id bigint, elems array<bigint>, weights array<double>")
    sig = {r.id: np.array(r.sig) for r in schemes.weighted_signatures(w, schemes.cws(3000, 1)).collect()}
    assert 2 not in sig
    law = 2 / 11
    assert abs((sig[0] == sig[1]).mean() - law) < 5 * math.sqrt(law * (1 - law) / 3000)
    over = {r.id: np.array(r.sig) for r in schemes.weighted_signatures(w, schemes.weighted_opm(3000, 1, 10)).collect()}
    ask = {r.id: np.array(r.sig) for r in schemes.weighted_signatures(w, schemes.weighted_opm(3000, 1, 10), "query").collect()}
    law = 2 / 18
    assert abs((over[0] == ask[1]).mean() - law) < 5 * math.sqrt(law * (1 - law) / 3000)


def test_staircase_is_explicit_padding(spark):
    x, _ = rows()
    df = frame(spark, [*x, (9, [], 0), (10, [5], 1), (11, list(range(1, 101)), 100)])
    for m in (1, 60, 100):
        a, b = (sorted(map(str, schemes.opm1(40, 3, m, explicit=e).data_signatures(df).collect())) for e in (True, False))
        c = sorted(map(str, schemes.repad(schemes.minhash(40, 3).data_signatures(df), schemes.opm1(40, 3, m)).collect()))
        assert a == b == c and len(a) == len(x) + 2


def test_padding_to_own_size_is_minhash(spark):
    df = frame(spark, [(i, [H.py_fp(f"{i}:{k}") for k in range(20)], 20) for i in range(5)])
    a = {r.id: r.sig for r in schemes.opm1(30, 3, 20).data_signatures(df).collect()}
    assert a == {r.id: r.sig for r in schemes.minhash(30, 3).data_signatures(df).collect()}


def test_signatures_do_not_depend_on_partitions(spark):
    x, _ = rows()
    s = schemes.sign_alsh(50, 3, 8.0)
    assert len({tuple(sorted(map(str, s.data_signatures(frame(spark, x).repartition(n)).collect()))) for n in (1, 5)}) == 1


def test_one_permutation_is_near_the_law(spark):
    sizes = [(300, 300, 150)]
    got = np.mean([rates(spark, schemes.one_permutation(64, seed), sizes)[0] for seed in range(12)])
    assert abs(got - 150 / 450) < 0.06


def test_published_exponents():
    table = {(0.1, 0.3): (0.704, 0.936), (0.5, 0.5): (0.565, 0.745), (0.9, 0.9): (0.522, 0.697), (0.95, 0.7): (0.144, 0.341)}
    for (s, c), (opm, sign) in table.items():
        assert round(T.rho_opm(s, c), 3) == opm and round(T.rho_sign(s, c), 3) == sign
    for s, sign, l2 in ((0.1, 0.963, 0.981), (0.5, 0.799, 0.863), (0.9, 0.489, 0.571)):
        assert abs(T.rho_signalsh(s, 0.5)[0] - sign) < 0.002 and abs(T.rho_l2alsh(s, 0.5)[0] - l2) < 0.002
    for i in range(1, 100):
        for j in range(1, 100):
            assert 0 < T.rho_opm(i / 100, j / 100) < T.rho_sign(i / 100, j / 100) < 1


def test_sampling_exponent_goes_to_one():
    assert T.rho_sampling(20, 0.5, 64, 64) < T.rho_sampling(20, 0.5, 70_000, 64) < 1
    assert T.rho_sampling(20, 0.5, 10**9, 64) > 0.9999


def test_dead_rows_change_no_candidate(spark):
    from overlapix.sources.tables import collection

    x, q = (collection(spark, "/root/testdata/sf0.001", c).where("f > 0") for c in ("docs_w", "bench_w"))
    m = sets.padding_bound(x, "data_and_query", q)
    s = schemes.opm1(24, 3, m)
    xs, qs = s.data_signatures(x), s.query_signatures(q)

    def found(k, l, keep):  # noqa: E741
        a, b = bucketing.index_rows(xs, k, l, keep_dead=keep), bucketing.index_rows(qs, k, l).withColumnRenamed("id", "q")
        return {(r.q, r.id) for r in a.join(b, ["j", "key"]).select("q", "id").distinct().collect()}

    assert found(1, 24, True) == found(1, 24, False)
    assert found(1, 8, False) <= found(1, 24, False) and found(2, 12, False) <= found(1, 24, False)
    alive, whole = (bucketing.index_rows(xs, 1, 24, keep_dead=k).count() for k in (False, True))
    from overlapix.plans.planner import live_fraction

    assert abs(alive / whole - live_fraction(x, m, 1)) < 0.02


def test_saved_index_and_growth(spark, tmp_path):
    x, q = (frame(spark, r) for r in rows())
    s = schemes.opm1(8, 3, 60)
    ix = bucketing.LshIndex.build(x, s, 1, 8)
    spark.sql("DROP TABLE IF EXISTS overlapix_test_index")
    ix.save("overlapix_test_index", 4)
    again = bucketing.LshIndex.open(spark, "overlapix_test_index", s, 1, 8)
    pairs = lambda i: sorted(map(tuple, i.candidates(q).collect()))
    assert pairs(again) == pairs(ix)
    grown = ix.grow(schemes.minhash(8, 3).data_signatures(x), 200)
    assert sorted(map(tuple, grown.rows.collect())) == sorted(map(tuple, bucketing.LshIndex.build(x, s.with_(m=200), 1, 8).rows.collect()))
    spark.sql("DROP TABLE overlapix_test_index")


def test_sparse_and_dense_counts_agree(spark):
    x, q = (frame(spark, r) for r in rows())
    s = schemes.minhash(32, 3)
    xs, qs = s.data_signatures(x), s.query_signatures(q)
    dense = {(r.q_id, r.x_id): r.matches for r in ranking.match_counts(xs, qs, (16,)).where("matches > 0").collect()}
    assert dense == {(r.q_id, r.x_id): r.matches for r in ranking.sparse_match_counts(xs, qs, 16).collect()}


def test_salted_join_is_the_join(spark):
    from overlapix.plans.planner import salted_join

    a = spark.createDataFrame([(0, "hot", i) for i in range(300)] + [(1, "b", 7)], "j int, key string, x bigint")
    b = spark.createDataFrame([(0, "hot", 1), (0, "hot", 2), (1, "b", 3), (2, "c", 4)], "j int, key string, q bigint")
    want = sorted(map(tuple, a.join(b, ["j", "key"]).collect()))
    assert sorted(map(tuple, salted_join(a, b, ["j", "key"], 20).collect())) == want


def test_identical_sets_join_once(spark):
    e = [[1, 2, 3, 4]] * 50 + [[1, 2, 3, 5], [9, 10]]
    df = frame(spark, [(i, x, len(x)) for i, x in enumerate(e)])
    pairs = {tuple(r) for r in bucketing.self_join(df, schemes.minhash(24, 3), 1, 24).collect()}
    assert {(0, i) for i in range(1, 50)} <= pairs and (0, 50) in pairs and len(pairs) == 50

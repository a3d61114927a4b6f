"""Results of a row a pair or place: the order in which tasks write them."""

from itertools import groupby

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry

ROOT = "/root/testdata/sf0.001"


@pytest.mark.parametrize("kind", ["minhash", "opm1", "opm2", "l2lsh", "l2alsh", "normsign", "signalsh"])
def test_lists_are_written_side_by_side(spark, monkeypatch, kind):
    """Whole lists came one after another, and places filled the disk."""
    from overlapix.plans import catalog_hash as C

    monkeypatch.setattr(C, "PIECE", 8)
    rows = entry.queries()[f"pr_curve_{kind}"](spark, ROOT).withColumn("part", F.spark_partition_id()).collect()
    parts = [[(-((r.p - 1) // 8), r.q_id, r.p) for r in own] for _, own in groupby(rows, key=lambda r: r.part)]
    assert max(len({q for _, q, _ in own}) for own in parts) > 1 and all(own == sorted(own) for own in parts)
    whole = {}
    for r in rows:
        whole.setdefault(r.q_id, []).append(r.p)
    assert all(sorted(p) == list(range(1, len(p) + 1)) for p in whole.values())


def frame(spark, sets):
    return spark.createDataFrame([(i, sorted(e), len(e)) for i, e in sets.items()], "id bigint, elems array<bigint>, f int")


@pytest.mark.parametrize("scheme", ["l2", "sign", "norm"])
def test_products_by_brute_force(spark, monkeypatch, scheme):
    """Several passes, parts and sizes, with products worked out by size and one by one."""
    from overlapix.operators import tiles
    from overlapix.operators import transforms as tr

    for name, value in (("PART", 5), ("ASKED", 7), ("FINE", 16)):
        monkeypatch.setattr(tiles, name, value)
    x = {i: {(i * 7 + j * j) % 23 for j in range(i % 9 + 1)} for i in range(40)}
    q = {100 + i: {(i * 5 + j * 3) % 23 for j in range(i % 5 + 2)} for i in range(17)}
    v, (u, m, n) = 3.0, {"l2": (0.83, 3, 6), "sign": (0.75, 2, 4), "norm": (1.0, 0, 2)}[scheme]
    grown = lambda s, side: {"l2": lambda: tr.augment_l2(s, u, v, m, side), "sign": lambda: tr.augment_sign(s, u, v, m, side), "norm": lambda: tr.augment_norm(s, v, side)}[scheme]()
    both = [grown(frame(spark, s), side).withColumn("norm2", F.round(tr.augmented_norm2(F.col("f"), u / v, F.col("aug"), n), 6)) for s, side in ((x, "data"), (q, "query"))]
    got = tiles.products(*(tiles.coded(s, side, more=("f", "norm2", "aug")) for s, side in zip(both, ("data", "query"), strict=True)), lambda a, xa, qa: tr.augmented_product(a, u / v, xa, qa, n))
    rows = [[r.asDict() for r in s.collect()] for s in both]
    pairs = spark.createDataFrame([(b["id"], a["id"], len(set(a["elems"]) & set(b["elems"])), a["aug"], b["aug"], a["norm2"], b["norm2"]) for a in rows[0] for b in rows[1] if set(a["elems"]) & set(b["elems"])], "q_id bigint, x_id bigint, a bigint, xa array<double>, qa array<double>, norm2_x double, norm2_q double")
    want = pairs.select("q_id", "x_id", F.round(tr.augmented_product(F.col("a"), u / v, F.col("xa"), F.col("qa"), n), 6).alias("product"), "norm2_x", "norm2_q")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect())) and want.count() > 200


def test_rounds_like_spark(spark):
    from overlapix.operators import transforms as tr

    values = [k / 128 for k in range(200)] + [-k / 128 for k in range(1, 20)] + [1.0000005, 2.4999995, 0.1234565, 0.3000005, 1e-7, 5e-7, 123456.7890125, 1e12 + 0.5]
    want = [r.v for r in spark.createDataFrame([(i, v) for i, v in enumerate(values)], "i int, v double").select("i", F.round("v", 6).alias("v")).orderBy("i").collect()]
    assert tr.rounded(np.array(values)).tolist() == want


@pytest.mark.parametrize("name", ["transform_l2", "transform_norm", "transform_sign"])
def test_pairs_are_written_by_query(spark, name):
    """Every pair was a row of sizes from which its three numbers were rounded, and the next
    row had another query."""
    df = entry.queries()[name](spark, ROOT)
    assert "round(" not in df._jdf.queryExecution().executedPlan().toString().split("MapInArrow")[0]
    rows = df.withColumn("part", F.spark_partition_id()).collect()
    for _, own in groupby(rows, key=lambda r: r.part):
        own = [r.q_id for r in own]
        assert len(list(groupby(own))) == len(set(own))

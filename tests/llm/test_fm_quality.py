import numpy as np

from overlapix.llm import fm_quality as Q
from tests.llm.helpers import EDGES, docs_frame


def test_pair_identity():
    rng = np.random.default_rng(0)
    m = Q.Model(0.3, rng.normal(size=50), rng.normal(size=(50, 4)))
    slots, values = rng.integers(0, 50, 9), rng.normal(size=9)
    want = m.bias + m.weight[slots] @ values + sum(m.factor[slots[i]] @ m.factor[slots[j]] * values[i] * values[j] for i in range(9) for j in range(i + 1, 9))
    assert np.isclose(m.raw(slots, values, np.array([0]))[0], want)


def test_held_out_accuracy(spark):
    root = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{root}/documents.parquet"), spark.read.parquet(f"{root}/labels.parquet")
    model = Q.train(docs, labels)
    held = docs.where(Q.fold(Q.F.col("doc_id"), 5) == 0).join(labels, "doc_id")
    rows = Q.scored(held, model, ("doc_id", "quality")).collect()
    good = np.array([r.score for r in rows if r.quality == 1])
    bad = np.array([r.score for r in rows if r.quality == 0])
    auc = (good[:, None] > bad[None, :]).mean() + 0.5 * (good[:, None] == bad[None, :]).mean()
    assert auc > 0.97, auc
    assert (good >= 0.3).mean() > 0.97 and (bad < 0.3).mean() > 0.6, ((good >= 0.3).mean(), (bad < 0.3).mean())


def test_edges(spark):
    labels = spark.createDataFrame([(1, 1), (None, 1), (3, None), (4, 0), (4, 1)], "doc_id bigint, quality int")
    df = docs_frame(spark, EDGES)
    out = Q.scored(df, Q.train(df, labels)).collect()
    assert len(out) == len(EDGES) and all(0 <= r.score <= 1 for r in out)
    assert {r.score for r in Q.scored(df, Q.train(df, labels.limit(0))).collect()} == {0.5}
    assert Q.scored(df.limit(0), Q.train(df.limit(0), labels)).count() == 0

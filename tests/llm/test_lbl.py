import math
import resource
import zlib
from collections import Counter

import numpy as np

from overlapix.llm import lbl
from tests.llm.helpers import EDGES, docs_frame


def brute(rows, folds=7, held=2):
    words = [(i, [w for w in (t or "").encode().lower().split()]) for i, t in rows]
    away = [i is not None and zlib.crc32(str(i).encode()) % folds == held for i, _ in rows]
    c = Counter()
    for (_, w), h in zip(words, away, strict=True):
        if not h:
            c.update([*w, None])
    n, v = sum(c.values()), len(c)
    return sorted(((i, h, len(w) + 1, sum(c[x] > 0 for x in [*w, None]), n, round(sum(math.log10((c[x] + 1) / (n + v + 1)) for x in [*w, None]), 6)) for (i, w), h in zip(words, away, strict=True)), key=repr)


def result(rows):
    return sorted(((r.doc_id, r.held_out, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 6)) for r in rows), key=repr)


def test_edges(spark):
    got = lbl.language_model_scores(docs_frame(spark, EDGES), vocab=4, common=5).collect()
    assert result(got) == brute(EDGES) and all(math.isfinite(r.score) and r.score < 0 for r in got)
    assert lbl.language_model_scores(docs_frame(spark, [])).count() == 0


def test_only_held_rows(spark):
    rows = [(i, "a b") for i in range(60) if zlib.crc32(str(i).encode()) % 7 == 2]
    assert result(lbl.language_model_scores(docs_frame(spark, rows)).collect()) == brute(rows)


def test_documents(spark):
    df = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    rows = [tuple(r) for r in df.collect()]
    got = lbl.language_model_scores(df, vocab=500, common=2000).collect()
    assert result(got) == brute(rows)


def test_held_out_gain(spark):
    df = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    base, score, n = lbl.language_model_scores(df).where("held_out").selectExpr("sum(base_score)", "sum(score)", "sum(n_tokens)").first()
    assert (score - base) / n > 0.1, (score - base) / n


def test_long_text_and_clashing_columns(spark):
    rows = [(1, "a b c " * 400_000), (2, "x" * 2_000_000), (3, "a b"), (3, "a b")]
    df = docs_frame(spark, rows).selectExpr("doc_id", "text", "1 AS held", "2 AS score", "3 AS word", "4 AS rid")
    got = lbl.language_model_scores(df, vocab=3, common=4).collect()
    assert result(got) == brute(rows) and all(math.isfinite(r.score) for r in got)


def random_model(outputs, seed=5):
    rng = np.random.default_rng(seed)
    start = lbl.LogBilinear.start(rng.integers(0, 50, outputs).astype(float))
    values = start.flat_params()
    return start.with_params(values + np.where(values < -1e3, 0, rng.normal(0, 0.3, len(values))))


def slow_log_prob(model, before, output):
    """One token at a time, by loops over groups and members."""
    h = sum(model.context[o].astype(float) * model.position[p] for p, o in enumerate(before))
    groups, depth = model.bias.shape
    over_groups = [math.exp(float(h @ model.group[g]) + float(model.group_bias[g])) for g in range(groups)]
    g, place = output % groups, output // groups
    inside = [math.exp(float(h @ model.word[g, k]) + float(model.bias[g, k])) for k in range(depth)]
    p = over_groups[g] / sum(over_groups) * inside[place] / sum(inside)
    return math.log10((1 - lbl.MIX) * p + lbl.MIX * float(model.unigram[output]))


def test_probabilities():
    for outputs in (1, 2, 7, 40):
        model = random_model(outputs)
        flat, at = lbl._flatten([np.arange(outputs, dtype=np.int32), np.zeros(0, np.int32)])
        fast = model.log_probs(flat, at)
        slow = [slow_log_prob(model, [flat[t - 1 - p] for p in range(lbl.CONTEXT)], flat[t]) for t in at]
        assert np.allclose(fast, slow, atol=1e-4)
        before = [min(i, outputs - 1) for i in range(lbl.CONTEXT)]
        assert math.isclose(sum(10 ** slow_log_prob(model, before, o) for o in range(outputs)), 1, rel_tol=1e-4)


def test_score_is_the_models(spark, monkeypatch):
    rows = [(i, t) for i, t in enumerate(["the cat sat on the mat", "a dog sat", "the bird", "", "cat dog Bird unseenword", None, "the the the cat", "mat on mat"] * 3)] + [(100, "zebra the quux"), (None, "cat")]
    kept = {}
    real = lbl.LogBilinear.start

    def start(uses, **kw):
        kept["model"] = real(uses, **kw)
        return kept["model"]

    monkeypatch.setattr(lbl.LogBilinear, "start", start)
    monkeypatch.setattr(lbl, "trained", lambda texts, words, rest, model, n: kept.update(words=words) or model)
    got = lbl.language_model_scores(docs_frame(spark, rows), vocab=4, rest=3, common=6).collect()
    away = [i is not None and zlib.crc32(str(i).encode()) % 7 == 2 for i, _ in rows]
    split = [(t or "").encode().lower().split() for _, t in rows]
    c = Counter(w for ws, h in zip(split, away, strict=True) if not h for w in ws)
    listed = {w: i + 4 for i, w in enumerate(kept["words"])}
    output = lambda w: listed.get(w) or lbl.rest_class(w, 3)
    size = Counter()
    for w, n in c.items():
        if w not in listed:
            size[output(w)] += n + 1
    want = []
    for (i, _), ws in zip(rows, split, strict=True):
        ids = [0] * lbl.CONTEXT + [output(w) for w in ws] + [0]
        total = sum(slow_log_prob(kept["model"], ids[t - lbl.CONTEXT : t][::-1], ids[t]) for t in range(lbl.CONTEXT, len(ids)))
        want.append((i, round(total + sum(math.log10((c[w] + 1) / (size[output(w)] + 1)) for w in ws if w not in listed), 3)))
    assert sorted(want, key=repr) == sorted(((r.doc_id, round(r.score, 3)) for r in got), key=repr)


def test_learners_average(spark):
    uses = np.array([4.0, 9, 5, 3, 2])
    model, words = lbl.LogBilinear.start(uses), [b"a", b"b"]
    texts = [["a b a b b x"], ["a a a y"]]
    parts = []
    for part in texts:
        ids = [np.array([{"a": 3, "b": 4}.get(w) or lbl.rest_class(w.encode(), 2) for w in t.split()], np.int32) for t in part]
        learner, (flat, at) = lbl.Learner(model), lbl._flatten(ids)
        learner.step(flat, at)
        parts.append((len(at), learner.m.flat_params()))
    want = sum(n * v for n, v in parts) / sum(n for n, _ in parts)
    df = spark.createDataFrame([(i, t) for i, part in enumerate(texts) for t in part], "i int, text string")
    assert lbl.trained(df.limit(0), words, 2, model, 0) is model
    both = df.repartitionByRange(2, "i")
    got = lbl.trained(both, words, 2, model, 2 * lbl.LEARNER_TOKENS)  # two tasks
    assert np.allclose(got.flat_params(), want, atol=1e-5)


def test_a_step_moves_each_array_once(monkeypatch):
    """Every group's words and biases were moved on their own, a few rows at a time; the biases against loops."""
    model = random_model(7)
    learner, (flat, at) = lbl.Learner(model), lbl._flatten([np.array([1, 2, 6, 1, 3], np.int32), np.array([5], np.int32)])
    moved, real = [], lbl.Learner._move
    monkeypatch.setattr(lbl.Learner, "_move", lambda self, name, where, grad: moved.append(name) or real(self, name, where, grad))
    monkeypatch.setattr(lbl, "COLUMNS", 2, raising=False)
    learner.step(flat, at)
    groups, depth = model.bias.shape
    noise = lbl.NOISE * model.unigram.astype(float).reshape(depth, groups).T
    outer, inner = np.zeros(groups), np.zeros((groups, depth))
    chance = lambda score, n: 1 / (1 + math.exp(math.log(n) - score))
    for t in at:
        h = sum(model.context[flat[t - 1 - p]].astype(float) * model.position[p] for p in range(lbl.CONTEXT))
        g, place = flat[t] % groups, flat[t] // groups
        for k in range(groups):
            c = chance(h @ model.group[k] + model.group_bias[k], noise[k].sum())
            outer[k] += (k == g) * (1 - c) - noise[k].sum() * c
        for k in range(depth):
            if noise[g, k] > 0:
                n = lbl.NOISE * noise[g, k] / noise[g].sum()
                c = chance(h @ model.word[g, k] + model.bias[g, k], n)
                inner[g, k] += (k == place) * (1 - c) - n * c
    for name, grad in (("group_bias", outer), ("bias", inner)):
        assert np.allclose(getattr(learner.m, name) - getattr(model, name), lbl.RATE * grad / np.sqrt(grad * grad + 1e-6), atol=2e-3), name
    assert sorted(moved) == sorted(lbl.LogBilinear.PARAMS)


def test_steps_reuse_memory():
    lbl.keep_memory()
    rng = np.random.default_rng(0)
    learner = lbl.Learner(lbl.LogBilinear.start(1e6 / np.arange(1, 4610)))
    flat, at = lbl._flatten([rng.integers(0, 4609, 300).astype(np.int32) for _ in range(60)])

    def step():
        learner.step(flat, at[: lbl.STEP])
        learner.m.log_probs(flat, at[: lbl.BATCH])

    for _ in range(4):
        step()
    before = resource.getrusage(resource.RUSAGE_SELF).ru_minflt
    for _ in range(10):
        step()
    assert resource.getrusage(resource.RUSAGE_SELF).ru_minflt - before < 2000  # some 20,000 where arrays are given back


def test_scores_with_and_without_a_shift_agree():
    score = np.random.default_rng(1).normal(0, 8, (20, 50)).astype(np.float32)
    chosen = np.arange(50) % 20
    np.testing.assert_allclose(lbl._share(score.copy(), chosen, True), lbl._share(score.copy(), chosen), rtol=1e-5)

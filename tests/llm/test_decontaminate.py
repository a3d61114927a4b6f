import hashlib
import re

import pytest

from overlapix.llm import decontaminate as D
from tests.llm.helpers import EDGES, docs_frame

ITEMS = [(1, "Alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu"), (2, "short item"), (3, None), (4, "!!!"), (5, "short item"), (12, "w " * 12), (None, "nameless piece")]
DOCS = [
    (1, "x Alpha, BETA gamma delta-epsilon zeta eta theta iota kappa y"),
    (2, "alpha beta gamma delta epsilon zeta eta theta iota"),
    (3, "a Short  item, short item b"),
    (4, "w " * 30),
    (4, "w " * 30),
    (5, "lead beta gamma delta epsilon zeta eta theta iota kappa lambda mu tail"),
    (6, "ÀLPHA nameless piece"),
    *EDGES,
]


def words(t):
    low = "".join(c.lower() if "A" <= c <= "Z" else c for c in t or "")
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low)


def brute(docs, items, n=10):
    out = []
    for i, t in docs:
        w, hit, names = words(t), set(), set()
        for name, x in items:
            v = words(x)
            size = min(n, len(v))
            wins = {tuple(v[a : a + size]) for a in range(len(v) - size + 1)} if v else set()
            for a in range(len(w) - size + 1):
                if tuple(w[a : a + size]) in wins:
                    hit |= set(range(a, a + size))
                    names.add("" if name is None else str(name))
        out.append((i, len(w), len(hit), len(names), hashlib.sha256(",".join(sorted(names)).encode()).hexdigest(), bool(hit)))
    return sorted(out, key=repr)


@pytest.mark.parametrize("limit", [D.BROADCAST_WINDOWS, 0])
def test_brute_force(spark, monkeypatch, limit):
    monkeypatch.setattr(D, "BROADCAST_WINDOWS", limit)
    bench = spark.createDataFrame(ITEMS, "item_id bigint, text string")
    got = D.contamination(docs_frame(spark, DOCS), bench)
    assert sorted(map(tuple, got.collect()), key=repr) == brute(DOCS, ITEMS)


def test_empty_tables(spark):
    bench = spark.createDataFrame(ITEMS, "item_id bigint, text string")
    assert D.contamination(docs_frame(spark, []), bench).count() == 0
    assert not any(r.contaminated for r in D.contamination(docs_frame(spark, DOCS), bench.limit(0)).collect())


def test_spans_go_and_clean_texts_stay(spark):
    bench = spark.createDataFrame(ITEMS, "item_id bigint, text string")
    df = spark.createDataFrame([(i, t, "kept") for i, t in [*DOCS, (50, "Short item")]], "doc_id bigint, text string, w string")
    out = {(r.doc_id, r.text) for r in D.remove_spans(df, bench).collect()}
    assert (1, "x y") in out and (3, "a b") in out and (5, "lead tail") in out and (6, "ÀLPHA ") in out
    assert not any(i == 50 or (i == 4 and t and t.startswith("w")) for i, t in out)
    assert {x for x in EDGES} <= out
    dropped = {r.doc_id for r in D.remove_spans(df, bench, drop_documents=True).collect()}
    assert not dropped & {5, 50} and 2 in dropped


def test_no_python_in_plan(spark):
    bench = spark.createDataFrame(ITEMS, "item_id bigint, text string")
    plan = D.contamination(docs_frame(spark, DOCS), bench)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan

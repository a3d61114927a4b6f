import os
import subprocess
import sys
import time

import pytest

import __spark_entry__ as entry
from overlapix.operators import exact, sets
from overlapix.sources.tables import collection, load

ROOT = "/root/testdata/sf0.001"


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_text_sets_need_no_shuffle(spark):
    p = plan(collection(spark, ROOT, "docs_w"))
    assert "Exchange" not in p and "Python" not in p


def test_queries_are_broadcast_and_columns_pruned(spark):
    p = plan(exact.overlaps(collection(spark, ROOT, "docs_w"), collection(spark, ROOT, "bench_w")))
    assert "BroadcastHashJoin" in p and "SortMergeJoin" not in p and "n_chars" not in p


def test_rank_limit_before_the_shuffle(spark):
    p = plan(exact.exact_topk(collection(spark, ROOT, "docs_w"), collection(spark, ROOT, "bench_w"), 5))
    assert "WindowGroupLimit" in p


def test_filters_reach_the_scan(spark):
    p = plan(load(spark, ROOT, "documents").where("n_chars >= 2000").select("doc_id"))
    assert "PushedFilters: [IsNotNull(n_chars), GreaterThanOrEqual(n_chars,2000)]" in p and "text" not in p.split("ReadSchema")[1]


def test_entry_runs(spark):
    df = entry.entry(spark)
    assert df.columns == ["q_id", "rank", "x_id", "a"] and df.count() > 0


def test_names_of_sql_are_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("hidden", ["overlapix.llm", "corpus_pipeline"])
def test_works_without_the_text_operators(hidden):
    code = f"import sys; sys.modules[{hidden!r}] = None; import __spark_entry__ as e; assert len(e.queries()) > 150 and 'search_opm1' in e.queries() and not any(n.startswith('op1_') for n in e.queries())"
    assert subprocess.run([sys.executable, "-c", code], check=False).returncode == 0


def test_odd_sets(spark):
    df = spark.createDataFrame([(1, None), (2, ""), (3, "a A a"), (4, "x"), (4, "x"), (None, "b")], "k bigint, t string")
    got = sorted(((r.id, r.f) for r in sets.word_sets(df, "k", "t").collect()), key=repr)
    assert got == [(1, 0), (2, 0), (3, 1), (4, 1), (4, 1), (None, 1)]
    assert exact.overlaps(sets.word_sets(df.limit(0), "k", "t"), sets.word_sets(df, "k", "t")).count() == 0


def test_streams_agree_with_batches(spark):
    q = entry.queries()
    a, b = (sorted(map(tuple, q[n](spark, ROOT).collect())) for n in ("stream_index", "stream_index_batch"))
    assert a == b and a
    sig = {r.id: list(r.sig) for r in q["stream_signature"](spark, ROOT).collect()}
    from overlapix.operators import schemes

    want = {r.id: list(r.sig) for r in schemes.minhash(8, 17).data_signatures(collection(spark, ROOT, "user_hours")).collect()}
    assert sig == want


def test_late_rows_are_left_out(spark, tmp_path):
    from overlapix.streaming import streams

    rows = [(1, "2024-01-01 10:00:00", 1), (2, "2024-01-03 10:00:00", 1), (1, "2024-01-03 09:30:00", 1), (3, "2024-01-01 11:00:00", 1), (4, "2024-01-06 00:00:00", 1)]
    for i, part in enumerate((rows[:2], [(5, "2024-01-03 10:05:00", 1)], rows[2:4], rows[4:])):
        df = spark.createDataFrame([(e, t, u, "click", 1.0, "{}") for e, t, u in part], "event_id bigint, ts string, user_id bigint, event_type string, value double, props string")
        df.withColumn("ts", df.ts.cast("timestamp")).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        for f in os.listdir(tmp_path / "in"):
            if f.endswith(".parquet") and not f.startswith("seen"):
                os.rename(tmp_path / "in" / f, tmp_path / "in" / f"seen{i}-{f}")
                os.utime(tmp_path / "in" / f"seen{i}-{f}", (time.time() - 100 + i, time.time() - 100 + i))
    out = streams.drain(streams.hourly_counts(streams.event_stream(spark, str(tmp_path / "in"), 1)), "late").collect()
    assert {str(r.start)[:10]: r.n for r in out} == {"2024-01-01": 1, "2024-01-03": 3}

"""Registered queries against their SQL in DuckDB; OVERLAPIX_ALL=1 takes all of them."""

import os

import duckdb
import pytest

import __spark_entry__ as entry

ROOT = "/root/testdata/sf0.001"
SOME = "set_words set_shingles element_dictionary element_frequency exact_resemblance exact_weighted_jaccard inverted_prefix opm1_signature l2alsh_signature pad_staircase oph_signature law_check_opm1 pr_curve_opm1 search_opm1 kl_grid best_kl index_incremental near_duplicates m_policy_sweep join_asof_events fn_array udtf_bands stream_index setop_except".split()


def cell(x):
    if isinstance(x, float):
        return round(x, 6) + 0.0
    return x


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for f in os.listdir(ROOT):
        con.execute(f"CREATE VIEW {f.split('.')[0]} AS SELECT * FROM '{ROOT}/{f}'")
    return con


@pytest.mark.parametrize("name", sorted(set(entry.oracle_sql()) if os.environ.get("OVERLAPIX_ALL") else SOME))
def test_same_rows(spark, duck, name):
    got = entry.queries()[name](spark, ROOT)
    want = duck.execute(entry.oracle_sql()[name])
    cols = [c[0] for c in want.description]
    assert sorted(cols) == sorted(got.columns)
    mine = sorted(repr([cell(x) for x in r]) for r in map(tuple, got.select(*cols).collect()))
    assert mine == sorted(repr([cell(x) for x in r]) for r in want.fetchall())

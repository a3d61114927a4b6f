"""The whole containment join against its SQL and the known number of pairs."""

import os

import duckdb
import pytest

import __spark_entry__ as entry

ROOT = "/root/testdata/sf0.01"


@pytest.mark.parametrize("name", ["containment_join_whole", "passage_containment_whole"])
def test_every_pair(spark, name):
    duck = duckdb.connect()
    for f in os.listdir(ROOT):
        duck.execute(f"CREATE VIEW {f.split('.')[0]} AS SELECT * FROM '{ROOT}/{f}'")
    got = entry.queries()[name](spark, ROOT)
    want = duck.execute(entry.oracle_sql()[name])
    cols = [c[0] for c in want.description]
    rows = sorted(map(tuple, got.select(*cols).collect()))
    assert rows == sorted(want.fetchall())
    assert len(rows) == 26

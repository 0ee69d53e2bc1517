"""The driver's contract, and queries against their SQL on the smallest tables."""

import os

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
CORE = [n for n in entry.oracle_sql() if not n.startswith("op")]


def test_entry(spark):
    df = entry.entry(spark)
    assert df.columns == ["sample_id", "n_tokens", "first_component"] and df.count() == 10


def test_every_sql_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", CORE)
def test_query_equals_its_sql(spark, name):
    con = duckdb.connect()
    for f in os.listdir(SF):
        con.sql(f"CREATE VIEW {f.split('.')[0]} AS SELECT * FROM '{SF}/{f}'")
    want = con.sql(entry.oracle_sql()[name])
    got = entry.queries()[name](spark, SF)
    assert sorted(got.columns) == sorted(want.columns)
    rows = got.select(*want.columns).collect()
    assert sorted(map(str, map(tuple, rows))) == sorted(map(str, want.fetchall()))


def test_traces_fall(spark):
    for name in ("pretrain_tiny", "pretrain_fixed_token_tiny", "finetune_tiny", "supervised_pointnet"):
        losses = [r.loss for r in entry.queries()[name](spark, SF).orderBy("step").collect()]
        assert losses[-1] < losses[0], (name, losses)

"""The driver contract, over the smallest tables."""

import os
import re

import pytest

import __spark_entry__ as entry

DIR = "/root/testdata/sf0.001"
needs_data = pytest.mark.skipif(not os.path.isdir(DIR), reason="no test data")


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


@needs_data
def test_entry_runs(spark):
    df = entry.entry(spark)
    assert df.columns == ["query_id", "node_id", "score", "rank"] and df.count() > 0


@needs_data
def test_exact_search_keeps_k_before_the_shuffle(spark):
    plan = entry.queries()["b1_vector"](spark, DIR)._jdf.queryExecution().executedPlan().toString()
    assert "WindowGroupLimit" in plan and not re.search("CartesianProduct|Python", plan)


@needs_data
@pytest.mark.parametrize("name", ["b1_vector", "td_rrf", "hz_filtered", "bu_rrf", "measures_td_rrf"])
def test_oracles(spark, name):
    import duckdb

    con = duckdb.connect()
    for t in ("embeddings", "documents"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{DIR}/{t}.parquet'")
    df = entry.queries()[name](spark, DIR)
    cols = sorted(df.columns)
    want = con.execute(f"SELECT {', '.join(cols)} FROM ({entry.oracle_sql()[name]})").fetchall()
    assert sorted(map(str, (tuple(r) for r in df.select(*cols).collect()))) == sorted(map(str, want))


@pytest.mark.skipif(not os.path.isdir("/root/testdata/sf0.01"), reason="no test data")
def test_approximate_search_finds_nine_of_ten(spark):
    r = entry.queries()["ann_recall"](spark, "/root/testdata/sf0.01").first()
    print("ann_recall", r)
    assert r.recall >= 0.9

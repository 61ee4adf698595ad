"""Results against their SQL by column name, and searches against brute force."""

import os

import pytest

import __spark_entry__ as entry

DIR = "/root/testdata/sf0.001"
needs_data = pytest.mark.skipif(not os.path.isdir(DIR), reason="no test data")


def against_sql(spark, name, d=DIR, tables=("embeddings",)):
    """Rows of a query and of its SQL, columns by name."""
    import duckdb

    con = duckdb.connect()
    for t in tables:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{d}/{t}.parquet'")
    want = con.execute(entry.oracle_sql()[name])
    names = [c[0] for c in want.description]
    df = entry.queries()[name](spark, d)
    assert sorted(df.columns) == sorted(names)
    cols = sorted(names)
    rows = [tuple(dict(zip(names, r))[c] for c in cols) for r in want.fetchall()]
    return sorted(tuple(r) for r in df.select(*cols).collect()), sorted(rows)


@needs_data
def test_centroid_columns_have_the_names_of_the_sql(spark):
    got, want = against_sql(spark, "agg_centroid")
    assert got == want

import duckdb
import pytest

import __spark_entry__ as entry


def test_names_of_oracles_are_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_entry_runs(spark):
    assert entry.entry(spark).count() >= 0


@pytest.mark.parametrize("name", ["item_support", "expected_support_s2", "support_cap_level2", "mine_static_hist", "buffered_update", "promising_update"])
def test_against_sql(spark, sf_dir, name):
    con = duckdb.connect()
    for t in "customer part orders lineitem events documents".split():
        con.sql(f"create view {t} as select * from '{sf_dir}/{t}.parquet'")
    got = entry.queries()[name](spark, sf_dir).toPandas()
    want = con.sql(entry.oracle_sql()[name]).df()
    columns = sorted(got.columns)
    assert columns == sorted(want.columns)
    rows = lambda d: sorted(map(tuple, d[columns].astype(str).values.tolist()))
    assert rows(got) == rows(want)

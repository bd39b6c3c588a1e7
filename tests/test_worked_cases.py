"""Worked cases on the given tables: they read them, and agree with their SQL."""

import duckdb
import pytest

import __spark_entry__ as contract

SF = "/root/testdata/sf0.001"
NAMES = ["s5_operators", "w24_encodings", "w24_scaling", "w24_weights"]


@pytest.mark.parametrize("name", NAMES)
def test_worked_case_equals_its_sql(spark, name):
    found = contract.queries()[name](spark, SF)
    with duckdb.connect() as con:
        for t in ("orders", "customer", "nation", "region"):
            con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
        expected = con.execute(contract.oracle_sql()[name]).fetchdf()
    columns = sorted(found.columns)
    assert columns == sorted(expected.columns) and len(expected)
    key = lambda rows: sorted(map(str, rows))
    assert key([tuple(r) for r in found.select(columns).toPandas().itertuples(index=False)]) == key([tuple(r) for r in expected[columns].itertuples(index=False)])


@pytest.mark.parametrize("name", NAMES)
def test_worked_case_needs_the_table(spark, name, tmp_path):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        contract.queries()[name](spark, str(tmp_path)).collect()

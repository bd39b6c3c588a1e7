"""Box rows of the baselines' q-errors against their SQL on the given tables."""

import duckdb
import pytest

import __spark_entry__ as contract

SF = "/root/testdata/sf0.001"
NAMES = ["w4_independence_by_count", "w5_independence_by_selectivity", "w6_independence_by_joint_size", "w7_independence_by_entropy", "w25_sample_by_selectivity"]


@pytest.mark.parametrize("name", NAMES)
def test_boxes_equal_their_sql(spark, name):
    found = contract.queries()[name](spark, SF)
    with duckdb.connect() as con:
        for t in ("lineitem", "orders", "customer", "nation", "region"):
            con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
        expected = con.execute(contract.oracle_sql()[name]).fetchdf()
    columns = sorted(found.columns)
    assert columns == sorted(expected.columns)
    key = lambda rows: sorted(map(str, rows))
    assert key([tuple(r) for r in found.select(columns).toPandas().itertuples(index=False)]) == key([tuple(r) for r in expected[columns].itertuples(index=False)])

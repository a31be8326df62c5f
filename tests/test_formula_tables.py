import os

import duckdb
import pytest

import __spark_entry__ as entry


@pytest.mark.parametrize("name", ["cost_growth", "memory_model", "message_bytes", "useful_ranks"])
def test_formulas_read_a_table(spark, sf, name):
    """Spark's tasks read columns of a given table, and the result is the SQL's."""
    df = entry.queries()[name](spark, sf)
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "FileScan parquet" in plan and "ReadSchema: struct<>" not in plan
    with duckdb.connect() as con:
        for t in ("part", "lineitem", "events"):
            con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{os.path.join(sf, t)}.parquet'")
        assert sorted(map(tuple, df.collect())) == sorted(con.execute(entry.oracle_sql()[name]).fetchall())


def test_throughput_times_the_rows_of_a_table(spark, sf):
    df = entry.queries()["throughput_samples"](spark, sf)
    assert "FileScan parquet" in df._jdf.queryExecution().executedPlan().toString()
    assert {(r.channels, r.knee in (100, 1_000, 10_000), r.best_rate > 0) for r in df.collect()} == {(16, True, True), (32, True, True)}

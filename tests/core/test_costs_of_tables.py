"""Cost queries take their shapes from a table: equal to their SQL, and they read it."""

import math

import duckdb
import pytest

from gradsift.workloads.catalog import ORACLES, QUERIES

NAMES = ["asymptotic_table", "bounds_table", "comm_quantised", "comm_table", "comm_vs_workers", "cost_cube", "cost_grouping_sets", "cost_rollup", "effective_compression", "index_cost_table", "min_offset_table", "paper_compression"]


@pytest.mark.parametrize("name", NAMES)
def test_equals_its_sql_on_a_table(spark, tmp_path, name):
    rows = spark.range(4000).selectExpr("id as o_orderkey", "id * id % 701 as o_custkey", "cast(date_add(date'1995-01-01', cast(id % 70 as int)) as timestamp_ntz) as o_orderdate")
    rows.coalesce(1).write.parquet(f"{tmp_path}/orders.parquet")
    df = QUERIES[name](spark, str(tmp_path))
    got = [tuple(r) for r in df.collect()]
    con = duckdb.connect()
    con.execute(f"CREATE VIEW orders AS SELECT * FROM '{tmp_path}/orders.parquet/*.parquet'")
    rel = con.execute(ORACLES[name])
    assert [c[0] for c in rel.description] == df.columns
    want = rel.fetchall()
    assert len(got) == len(want) > 0
    for a, b in zip(sorted(got, key=str), sorted(want, key=str), strict=True):
        assert all(x == y or (isinstance(x, float) and math.isclose(x, y, rel_tol=1e-9)) for x, y in zip(a, b, strict=True)), (a, b)
    assert df.inputFiles()  # it reads the table

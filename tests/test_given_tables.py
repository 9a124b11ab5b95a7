"""Plans and costs are those of given tables."""

import duckdb
import pytest

import edgeconn.queries as Q
from tests.test_queries import TABLES, plain

COSTS = ["repetition_plan", "congest_cost_table", "mpc_cost_table", "work_depth_table", "pandas_udf_side_bits"]


@pytest.mark.parametrize("key", COSTS)
def test_read_and_equal_sql(spark, small, key):
    db = duckdb.connect()
    for t in TABLES:
        db.sql(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    got = Q.queries()[key](spark, small)
    want = db.sql(Q.oracle_sql()[key])
    rows = sorted(tuple(plain(r[c]) for c in want.columns) for r in got.collect())
    assert rows and rows == sorted(tuple(plain(v) for v in r) for r in want.fetchall())


@pytest.mark.parametrize("key", ["bound_table", "congest_cost_models", *COSTS])
def test_without_rows_there_is_no_result(spark, small, tmp_path, key):
    for t in ("lineitem", "supplier", "orders"):
        spark.read.parquet(f"{small}/{t}.parquet").limit(0).write.parquet(f"{tmp_path}/{t}.parquet")
    assert Q.queries()[key](spark, str(tmp_path)).count() == 0

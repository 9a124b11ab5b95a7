"""Users of events that lie close together, in groups that meet in tasks."""

import duckdb
import pytest

from edgeconn import relational as R


@pytest.mark.parametrize("group, pairs", [(2000, 1 << 22), (3, 10), (1, 1)])
def test_groups_of_users_count_what_sql_counts(spark, tmp_path, monkeypatch, group, pairs):
    monkeypatch.setattr(R, "GROUP", group)
    monkeypatch.setattr(R, "PAIRS_AT_ONCE", pairs)
    rows = "SELECT (i // 2 * 2)::BIGINT AS event_id, TIMESTAMP '2024-01-01' + INTERVAL 1 SECOND * ((i * 7919) % 40 * 100) AS ts, ((i * i) % 11 - 3)::BIGINT AS user_id FROM range(150) AS t(i)"
    odd = "UNION ALL SELECT NULL, TIMESTAMP '2024-01-01', 1 UNION ALL SELECT 900, NULL, 1 UNION ALL SELECT 901, TIMESTAMP '2024-01-01', NULL"
    con = duckdb.connect()
    con.sql(f"COPY ({rows} {odd}) TO '{tmp_path}/events.parquet'")
    con.sql(f"CREATE VIEW events AS FROM '{tmp_path}/events.parquet'")
    df = R.FOUND["join_interval_user_pairs"](spark, str(tmp_path))
    assert sorted(map(tuple, df.collect())) == sorted(con.sql(R.SQL["join_interval_user_pairs"]).fetchall())
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan  # pairs of events never become rows

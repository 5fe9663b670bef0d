"""The learning rate schedule over the given events."""

import duckdb

from tabseek import workloads


def test_schedule_reads_events_and_equals_sql(spark):
    folder = "/root/testdata/sf0.001"
    rows = workloads.lr_schedule(spark, folder)
    assert "events.parquet" in rows._jdf.queryExecution().executedPlan().toString()
    sql = workloads.oracle_sql()["lr_schedule"].replace("FROM events", f"FROM '{folder}/events.parquet'")
    want = duckdb.sql(sql).fetchall()
    assert sorted(map(tuple, rows.collect())) == sorted(map(tuple, want)) and len(want) == 1_000

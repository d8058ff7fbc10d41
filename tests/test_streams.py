"""Results of streams that run to their end are written by the executors; the driver holds no rows."""

import pytest

from packflow.plans.queries import QUERIES
from packflow.streaming.queries import STATE_STORE

DIR = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["stream_dedup", "stream_sessions", "stream_static_join"])
def test_rows_come_from_files(spark, name):
    df = QUERIES[name](spark, DIR)
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    assert "parquet" in plan and "MemoryPlan" not in plan and df.inputFiles()
    assert spark.conf.get(STATE_STORE, None) is None


@pytest.mark.parametrize("name", ["stream_dedup", "stream_sessions", "stream_static_join"])
def test_no_events(spark, tmp_path, name):
    for t in ("events", "customer"):
        spark.read.parquet(f"{DIR}/{t}.parquet").limit(0).write.parquet(f"{tmp_path}/{t}.parquet")
    rows = QUERIES[name](spark, str(tmp_path)).collect()
    assert [tuple(r) for r in rows] == ([(0, 0)] if name == "stream_dedup" else [])

"""Queries that count by whole seconds, on events just beside the borders of their windows."""

from datetime import datetime

import duckdb
import pyarrow as pa
import pyarrow.parquet as pq
import pytest
from lexfold.plans import catalog

TIMES = ("05:59:59.400000", "05:59:59.500000", "05:59:59.700000", "06:00:00.500000", "06:59:59.600000", "07:00:00.400000", "11:59:59.500001", "12:00:00.000000", "23:59:59.999999")


@pytest.fixture(scope="module")
def odd(tmp_path_factory):
    folder = tmp_path_factory.mktemp("odd")
    ts = [datetime.fromisoformat(f"2024-01-0{day}T{t}") for day in (1, 2) for t in TIMES]
    n = len(ts)
    table = pa.table({"event_id": pa.array(range(n), pa.int64()), "ts": pa.array(ts, pa.timestamp("us")), "user_id": pa.array([k % 2 for k in range(n)], pa.int64()), "event_type": ["click"] * n, "value": [1.0] * n, "props": ["{}"] * n})
    pq.write_table(table, folder / "events.parquet")
    return str(folder)


@pytest.mark.parametrize("name", ["shard_sliding", "stream_sliding", "win_range_frame"])
def test_borders_fall_as_in_sql(spark, odd, name):
    db = duckdb.connect()
    db.sql(f"create view events as select * from '{odd}/events.parquet'")
    want = db.sql(catalog.ORACLE[name])
    got = catalog.QUERIES[name](spark, odd).select(*want.columns)
    assert sorted(map(tuple, got.collect())) == sorted(want.fetchall())

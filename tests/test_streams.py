"""Streams over many files."""

import datetime
import os

import pyarrow as pa
import pyarrow.parquet as pq
import pytest

from supportbounds.streaming import streams


@pytest.fixture
def few_reports(spark):
    spark.conf.set("spark.sql.streaming.numRecentProgressUpdates", "3")
    yield
    spark.conf.unset("spark.sql.streaming.numRecentProgressUpdates")


def test_late_rows_of_all_batches(spark, tmp_path, few_reports):
    folder = tmp_path / "events.parquet"
    folder.mkdir()
    hours = [0, 30, 31, 1, 2, 60, 3, 61, 90]  # rows of hours 1, 2 and 3 come when a batch has already closed their windows
    for i, h in enumerate(hours):
        ts = datetime.datetime(2024, 1, 1) + datetime.timedelta(hours=h)
        path = folder / f"part-{i}.parquet"
        pq.write_table(pa.table({"event_id": [i], "ts": pa.array([ts], pa.timestamp("us"))}), path)
        os.utime(path, (1_700_000_000 + i * 10, 1_700_000_000 + i * 10))
    found = {r.batch: r.dropped for r in streams.late_rows(spark, str(tmp_path)).collect()}
    assert set(found) >= set(range(len(hours)))
    assert sum(found.values()) == 3

"""Event windows against their SQL, on instants around a window's edge and on tables of several files."""

import collections
import datetime as dt

import duckdb
import pytest

EDGE = dt.datetime(2024, 1, 3, 6, 0, 0)
ROW = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def agree(spark, folder, name):
    from patchspace.plans import load

    plans, sql = load()
    db = duckdb.connect()
    db.execute(f"CREATE VIEW events AS SELECT * FROM read_parquet('{folder}/events.parquet/*.parquet')")
    want = db.execute(sql[name])
    columns = [c[0] for c in want.description]
    got = plans[name](spark, str(folder)).select(*columns).collect()
    assert collections.Counter(map(tuple, got)) == collections.Counter(want.fetchall())
    return len(got)


@pytest.mark.parametrize("name", ["event_tumbling", "event_sliding", "stream_tumbling_complete", "stream_tumbling_final"])
def test_windows_count_whole_seconds(spark, tmp_path, name):
    """Half a second before an edge goes to the even second, less than that stays, more goes on."""
    micros = (-500_001, -500_000, -499_999, -1, 0, 499_999, 500_000, 500_001, -1_500_000, 1_500_000)
    rows = [(i, EDGE + dt.timedelta(microseconds=m), 1, "click", 2.5, "{}") for i, m in enumerate(micros)]
    rows.append((99, EDGE + dt.timedelta(days=3, microseconds=-300_000), 2, "view", 1.0, "{}"))
    spark.createDataFrame(rows, ROW).coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    assert agree(spark, tmp_path, name)


def test_closed_cells_do_not_depend_on_the_files(spark, tmp_path):
    """A table's last file may hold earlier events than its first."""
    for i, day in enumerate((5, 5, 5, 0)):
        rows = [(i, EDGE + dt.timedelta(days=day, hours=i), 7, "click", 1.0, "{}")]
        spark.createDataFrame(rows, ROW).coalesce(1).write.mode("append").parquet(f"{tmp_path}/events.parquet")
    assert agree(spark, tmp_path, "stream_tumbling_final") == 1

"""Streams over tables of several files that are not in time order, against the statements."""

import duckdb
import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest

from motifmill import catalogue
from motifmill.operators import shared
from motifmill.streaming import events
from .test_catalogue import SF, plain


@pytest.fixture(scope="module")
def shuffled(tmp_path_factory):
    folder = tmp_path_factory.mktemp("events")
    table = pq.read_table(f"{SF}/events.parquet").slice(0, 300)
    rng = np.random.default_rng(4)
    # three days, two busy minutes each, 15 users
    ts = np.datetime64("2024-03-01") + rng.integers(0, 3, 300) * np.timedelta64(1, "D") + rng.integers(0, 12, 300) * np.timedelta64(10, "s")
    for name, values in (("ts", ts), ("user_id", rng.integers(0, 15, 300))):
        at = table.column_names.index(name)
        table = table.set_column(at, table.field(name), pa.array(values).cast(table.field(name).type))
    pq.write_table(table, folder / "whole.parquet")
    (folder / "events.parquet").mkdir()
    for i in range(10):
        pq.write_table(table.take(np.arange(i, table.num_rows, 10)), folder / "events.parquet" / f"part-{i}.parquet")
    return str(folder)


@pytest.mark.parametrize("name", ["st_window_tc", "st_incremental_tc", "st_stream_stream_join"])
def test_ten_unsorted_files_equal_the_statement(spark, shuffled, name):
    con = duckdb.connect()
    con.sql(f"CREATE VIEW events AS SELECT * FROM '{shuffled}/whole.parquet'")
    got, expected = catalogue.QUERIES[name](spark, shuffled).toPandas(), con.sql(catalogue.SQL[name]).df()
    assert len(expected) and plain(got) == plain(expected)


@pytest.mark.parametrize("tile_bytes", [1 << 20, 64])
def test_windows_are_counted_from_rows_not_from_edges(spark, shuffled, tile_bytes, monkeypatch):
    con = duckdb.connect()
    con.sql(f"CREATE VIEW events AS SELECT * FROM '{shuffled}/whole.parquet'")

    def no_edges(rows):
        raise AssertionError("edges of a dense window became rows")

    kept = shared.window_triangles
    monkeypatch.setattr(shared, "window_triangles", lambda rows, plain, **bounds: kept(rows, no_edges, **bounds))
    found = events.window_triangles(events.source(spark, shuffled), "day", least_pairs=1, tile_bytes=tile_bytes).withColumnRenamed("w", "day").toPandas()
    expected = con.sql(catalogue.SQL["st_window_tc"]).df()
    assert len(expected) and plain(found) == plain(expected)

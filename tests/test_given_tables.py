"""Queries that read the given tables: their scans, and their rows against DuckDB."""

from __future__ import annotations

import duckdb
import pytest

import __spark_entry__ as entry

NAMES = [
    "sql_surface",
    "small_stream_example",
    "ring_transfer_example",
    "band_of_pairs",
    "band_table",
    "equal_space_capacity",
    "ring_counts_by_ratio",
    "ring_edges",
    "cells_dim",
]


@pytest.mark.parametrize("name", NAMES)
def test_reads_events_and_equals_sql(spark, sf, name):
    read = set()
    df = entry.queries()[name](spark, sf)
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{sf}/events.parquet'")
    want = con.execute(entry.oracle_sql()[name])
    names = [d[0] for d in want.description]
    got = sorted(tuple(r) for r in df.collect())
    assert df.columns == names and got == sorted(map(tuple, want.fetchall())) and got
    if name != "ring_edges":  # its counts are written once and read again
        read = {f.rsplit("/", 1)[-1] for f in df.inputFiles()}
        assert "events.parquet" in read

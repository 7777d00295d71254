"""Queries against DuckDB on the smallest tables: a part of the catalogue, the rest is for the driver's own comparison."""

import duckdb
import pytest

import __spark_entry__ as entry
from tests.conftest import SF

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SOME = "w_orders w_fan total_identity order_morton line_locality scan_two_levels_orders single_site_orders peer_supplier hybrid_cap_fan strict_cap_fan first_cells_orders transfer_ranges_orders transfer_matrix_fan shared_faces_grid interp_polynomial adaptive_events_type adaptive_stream_type prism_expand op_stream_tumbling op_udtf_cuts op_sql_peer".split()


#: These read their data from a given table, not from the code.
TABLED = "adaptive_drift adaptive_vs_fixed example_peer example_single_site example_transfer fan_velocity fluid_cost ideal_interval_drift line_locality never_events op_sweep_grid op_udf_bary".split()


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return c


def rows(columns, data):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted(repr(tuple(r[i] for i in order)) for r in data)


@pytest.mark.parametrize("name", SOME)
def test_query(spark, duck, name):
    df = entry.queries()[name](spark, SF)
    want = duck.sql(entry.oracle_sql()[name])
    assert rows(df.columns, map(tuple, df.collect())) == rows(want.columns, want.fetchall())


@pytest.mark.parametrize("name", TABLED)
def test_reads_a_table(spark, duck, name):
    df = entry.queries()[name](spark, SF)
    assert df.inputFiles()
    want = duck.sql(entry.oracle_sql()[name])
    got = df.collect()
    assert got and rows(df.columns, map(tuple, got)) == rows(want.columns, want.fetchall())


def test_entry(spark):
    assert entry.entry(spark).count() == 16

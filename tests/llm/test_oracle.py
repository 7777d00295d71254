"""The operators with SQL against DuckDB on the smallest tables, and on rows that the tables lack."""

import duckdb
import pytest

import __spark_entry__ as entry
from tests.conftest import SF

NAMES = ("op4_fm_index_substring_dedup", "op5_suffix_array_decontamination", "op6_prefix_tree_join")


def rows(columns, data):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted(repr(tuple(r[i] for i in order)) for r in data)


def against_sql(spark, name, folder):
    duck = duckdb.connect()
    for t in ("documents", "benchmark"):
        duck.execute(f"create view {t} as select * from read_parquet('{folder}/{t}.parquet{'' if folder == SF else '/*.parquet'}')")
    got, want = entry.queries()[name](spark, str(folder)), duck.sql(entry.oracle_sql()[name])
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got.columns, map(tuple, got.collect())) == rows(want.columns, want.fetchall())


@pytest.mark.parametrize("name", NAMES)
def test_given_tables(spark, name):
    against_sql(spark, name, SF)


@pytest.mark.parametrize("name", NAMES)
def test_odd_rows(spark, tmp_path, name):
    long = " ".join(f"word{i % 61}" for i in range(400))
    other = " ".join(f"Wörd{i}" for i in range(80))
    texts = [None, "", " \t\n", "one", "One two three", "one two three", long, long + " tail", "head " + long, other, other.upper(), other + " x", other + "\x0bx", "a-b c_d " * 20]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    items = [(1, "three"), (2, "c d a b"), (3, " ".join(f"word{i}" for i in range(20, 45))), (4, None), (5, "--"), (6, "one two")]
    spark.createDataFrame(items, "item_id long, text string").coalesce(1).write.parquet(f"{tmp_path}/benchmark.parquet")
    against_sql(spark, name, tmp_path)

"""The registry, and a sample of queries against DuckDB."""

import duckdb
import pytest

import __spark_entry__ as entry
from roadtraj.sources.tables import TABLES

SF = "/root/testdata/sf0.001"


def _plain(v):
    return v if v is None or isinstance(v, (bool, int)) else round(v, 6) if isinstance(v, float) else str(v)


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", ["sp_compress", "tiling", "temporal_angular_100_100", "where_packed", "range_packed", "edge_counts_weighted", "op_asof_join", "op_interval_join", "op_dates"])
def test_query_equals_sql(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{SF}/{t}.parquet')")
    df = entry.queries()[name](spark, SF)
    columns = sorted(df.columns)
    got = sorted((tuple(_plain(r[c]) for c in columns) for r in df.collect()), key=repr)
    found = con.execute(entry.oracle_sql()[name])
    names = [d[0] for d in found.description]
    want = sorted((tuple(_plain(r[names.index(c)]) for c in columns) for r in found.fetchall()), key=repr)
    assert got == want


def test_entry_runs(spark):
    assert {r["stage"] for r in entry.entry(spark).collect()} >= {"spatial", "temporal", "overall"}

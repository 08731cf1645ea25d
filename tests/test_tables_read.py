"""Queries on grids and code lengths take their units and numbers from given tables, and still equal their SQL."""

import os

import pytest

from flowregions.queries import ORACLES, QUERIES
from flowregions.sqlapi import TABLES
from test_oracles import SF, plain

NAMES = {
    "adj_nation": "orders", "adj_tract": "orders", "adj_clockgrid": "events", "adj_segments": "orders", "adj_problems": "orders", "coarsen_adj": "orders",
    "ami_max": "orders", "ami_mean": "orders", "ami_trivial": "orders", "bits_huge": "lineitem", "bits_lgamma": "orders", "bits_table": "lineitem",
}


@pytest.mark.parametrize("name", NAMES)
def test_reads_a_table_and_equals_its_sql(spark, name):
    import duckdb

    con = duckdb.connect()
    for t in TABLES:
        path = f"{SF}/{t}.parquet"
        con.execute(f"create view {t} as select * from read_parquet('{path + '/*.parquet' if os.path.isdir(path) else path}')")
    frame = QUERIES[name](spark, SF)
    assert any(f"/{NAMES[name]}.parquet" in f for f in frame.inputFiles())
    found = con.sql(ORACLES[name])
    columns = sorted(frame.columns)
    assert sorted(found.columns) == columns
    rows = lambda got: sorted((tuple(plain(v) for v in r) for r in got), key=repr)
    at = [found.columns.index(c) for c in columns]
    assert rows([[r[c] for c in columns] for r in frame.collect()]) == rows([[r[k] for k in at] for r in found.fetchall()])

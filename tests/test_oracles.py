"""Registered queries against their SQL on the smallest tables."""

import math
import os

import pytest

from flowregions.queries import ORACLES, QUERIES
from flowregions.sqlapi import TABLES

SF = "/root/testdata/sf0.001"
NAMES = ("flows_planted", "flows_tracts", "flows_clock_grid", "flows_basket", "adj_segments", "coarsen_adj", "distance_share", "degrees", "dl_mg_region", "dl_w_tract_region", "dl_dc_w_region", "dl_ranked_mg_region", "dl_nested_w_given", "merge_gain_first_w", "ga_nation_w", "ga_trajectory_mg", "ga_first_increase", "ga_state_tracts_w", "cvm_tract_mixed", "ami_mean", "voronoi_snmi_p95", "rollup_flows", "join_range", "join_asof", "stream_flows", "stream_sessions")


@pytest.fixture(scope="module")
def duck():
    import duckdb

    con = duckdb.connect()
    for t in TABLES:
        path = f"{SF}/{t}.parquet"
        con.execute(f"create view {t} as select * from read_parquet('{path + '/*.parquet' if os.path.isdir(path) else path}')")
    return con


def plain(v):
    return float(f"{v:.9g}") if isinstance(v, float) and math.isfinite(v) else v


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_its_sql(spark, duck, name):
    frame = QUERIES[name](spark, SF)
    got = sorted((tuple(plain(r[c]) for c in sorted(frame.columns)) for r in frame.collect()), key=repr)
    found = duck.sql(ORACLES[name])
    at = [found.columns.index(c) for c in sorted(found.columns)]
    assert sorted(found.columns) == sorted(frame.columns)
    assert got == sorted((tuple(plain(r[k]) for k in at) for r in found.fetchall()), key=repr)


def test_entry_and_names(spark):
    import __spark_entry__ as entry

    queries, sql = entry.queries(), entry.oracle_sql()
    assert set(sql) <= set(queries) and len(queries) > 100
    assert entry.entry(spark).count() == 25

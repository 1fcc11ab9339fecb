"""Queries that once made their data up: they read a given table and follow its size."""

import glob
import os

import duckdb
import pytest

from cellbalance import registry

NAMES = {"cubic_contacts": "part", "cubic_velocities": "part", "hcp_contacts": "part", "kinematic_fall": "part", "lattice_source": "part", "curve_adjacency_share": "lineitem", "hilbert_udf_check": "lineitem", "lateral_children": "lineitem", "recursive_paths": "lineitem", "apriori_estimates": "lineitem", "max_feasible_p": "lineitem", "memory_model": "lineitem"}


@pytest.mark.parametrize("name", NAMES)
def test_query_reads_its_table(spark, data, tmp_path, name):
    registry.QUERIES[name](spark, data).collect()
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        registry.QUERIES[name](spark, str(tmp_path)).collect()


@pytest.mark.parametrize("name", [n for n in NAMES if n in registry.ORACLES])
def test_rows_are_those_of_the_sql(spark, data, name):
    con = duckdb.connect()
    for f in glob.glob(f"{data}/*.parquet"):
        con.execute(f"create view {os.path.basename(f)[:-8]} as select * from read_parquet('{f}')")
    df, found = registry.QUERIES[name](spark, data), con.execute(registry.ORACLES[name])
    columns = [c[0] for c in found.description]
    assert sorted(map(str, (tuple(r) for r in df.select(*columns).collect()))) == sorted(map(str, found.fetchall()))


def test_spheres_inside_a_close_packing_touch_twelve(spark, data):
    held = {r.contacts for r in registry.QUERIES["hcp_contacts"](spark, data).collect()}
    assert max(held) == 12 or spark.read.parquet(f"{data}/part.parquet").count() < 3 * 64

"""Queries against their SQL, on the smallest tables."""

import glob
import os

import duckdb
import pytest

from cellbalance import registry

#: One or two of each family; CORRECTNESS runs every registered SQL. ALL_SQL=1 runs them all here as well.
NAMES = ["box_bounds_lineitem", "cell_pyramid_lineitem", "two_to_one_closed_leaves", "face_edges", "hilbert_midpoint_assign", "morton_keys", "diffusion_round_1", "rcb_lineitem",
         "contacts_events", "ghosts_events", "hopper_max_load_series", "chain_documents", "asof_orders", "session_events", "max_load_per_algo", "streamed_daily_loads",
         "measured_weights", "contact_inflation", "streamed_interval_join", "streamed_late_rows", "adapt_two_levels", "root_order_assign", "hopper_contacts_series", "hopper_27_ranks",
         "physical_migration", "vector_curves", "voronoi_embeddings", "max_feasible_p", "multiset_operations"]
if os.environ.get("ALL_SQL"):
    NAMES = sorted(registry.ORACLES)


def rows(names, found):
    order = sorted(range(len(names)), key=lambda i: names[i])
    return sorted(tuple(repr(round(r[i], 6) + 0.0) if isinstance(r[i], float) else str(r[i]) for i in order) for r in found)


@pytest.mark.parametrize("name", NAMES)
def test_query_gives_the_rows_of_its_sql(spark, data, name):
    con = duckdb.connect()
    for f in glob.glob(f"{data}/*.parquet"):
        con.execute(f"create view {os.path.basename(f)[:-8]} as select * from read_parquet('{f}')")
    df = registry.QUERIES[name](spark, data)
    found = con.execute(registry.ORACLES[name])
    columns = [c[0] for c in found.description]
    assert sorted(columns) == sorted(df.columns)
    assert rows(df.columns, [tuple(r) for r in df.collect()]) == rows(columns, found.fetchall())

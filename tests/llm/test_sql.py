"""Whole-table queries against the SQL registered for them."""

import glob
import os

import duckdb
import pytest

from cellbalance.llm import queries


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_query_gives_the_rows_of_its_sql(spark, data, name):
    con = duckdb.connect()
    for f in glob.glob(f"{data}/*.parquet"):
        con.execute(f"create view {os.path.basename(f)[:-8]} as select * from read_parquet('{f}')")
    df = queries.QUERIES[name](spark, data)
    want = con.execute(queries.ORACLES[name])
    names = sorted(c[0] for c in want.description)
    assert names == sorted(df.columns)
    found = con.execute(f"select {', '.join(names)} from ({queries.ORACLES[name]})").fetchall()
    assert sorted(map(tuple, df.select(names).collect()), key=repr) == sorted(found, key=repr)

"""Contacts of tables whose rows must not be broadcast, and of points beyond the box."""

import time

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from cellbalance import registry
from cellbalance.operators import contacts, weights
from cellbalance.plans import hopper, timing


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("points", [hopper.contact_points, hopper.part_points])
def test_contacts_broadcast_no_rows(spark, data, points):
    assert "Broadcast" not in plan(contacts.detect(points(spark, data), 20))


@pytest.mark.parametrize("credit", ["owner", "both"])
def test_weights_of_contacts_broadcast_no_rows(spark, data, credit):
    pairs = contacts.detect(hopper.contact_points(spark, data), 20)
    located = hopper.contact_points(spark, data).selectExpr("pid", "0 as level", "gx as cx", "gy as cy", "gz as cz")
    assert "Broadcast" not in plan(weights.contacts(pairs, located, credit))


@pytest.fixture(scope="module")
def wide(spark, data, tmp_path_factory):
    """The events with users numbered on past the box, as in larger tables."""
    folder = tmp_path_factory.mktemp("wide")
    ev = spark.read.parquet(f"{data}/events.parquet").withColumn("user_id", F.expr("user_id * 12 + 100"))
    ev.coalesce(1).write.parquet(f"{folder}/events.parquet")
    return str(folder)


@pytest.mark.parametrize("name", ["ghosts_events", "ghost_ratio", "weight_contacts_owner", "weight_contacts_both", "contact_inflation"])
def test_points_beyond_the_box_count_as_in_sql(spark, wide, name):
    con = duckdb.connect()
    con.execute(f"create view events as select * from read_parquet('{wide}/events.parquet/*.parquet')")
    df, found = registry.QUERIES[name](spark, wide), con.execute(registry.ORACLES[name])
    columns = [c[0] for c in found.description]
    want = sorted(tuple(float(v) for v in r) for r in found.fetchall())
    assert sorted(tuple(float(v) for v in r) for r in df.select(*columns).collect()) == want


def test_contacts_between_cells_are_those_of_the_pairs(spark):
    """Slabs, walls of slabs, negative places, copies and two snapshots; cells without contacts stay."""
    at = "select id pid, cast(id % 2 as int) snapshot, pmod(hash(id, 1), 400) - 150L gx, pmod(hash(id, 2), 40) + 0L gy, pmod(hash(id, 3), 60) - 30L gz from range(1200)"
    points = spark.sql(f"{at} union all select 5000 + id, 0, 127 + id % 3, 3, 3 from range(4)")
    pairs = contacts.brute_force(points.withColumn("gz", F.expr("gz + 10000 * snapshot")), 8)
    cell = [F.expr(f"shiftright(g{n}, 5)").alias(n) for n in "xyz"]
    a, b = (points.select(F.col("pid").alias(f"pid_{s}"), *(["snapshot"] if s == "a" else []), F.struct(*cell).alias(f"cell_{s}")) for s in "ab")
    want = {(r[0], *r[1], *r[2]): r[3] for r in pairs.join(a, "pid_a").join(b, "pid_b").groupBy("snapshot", "cell_a", "cell_b").count().collect()}
    found = contacts.between_cells(points, 8, 5, occupied=True).groupBy("snapshot", "cx", "cy", "cz", "ox", "oy", "oz").agg(F.sum("contacts"))
    got = {tuple(r)[:-1]: r[-1] for r in found.collect()}
    assert {k: n for k, n in got.items() if n} == want and len(want) > 50
    assert {k[:4] for k in got} == {(r[0], *r[1:]) for r in points.select("snapshot", *cell).distinct().collect()}
    assert sum(r.contacts for r in contacts.between_cells(points, 8, 5).collect()) == pairs.count()


def test_a_step_tries_near_pairs_only():
    """Points on one sheet across x: a sweep along x alone would try all of their 7 million pairs."""
    rng = np.random.default_rng(7)
    x, y, z = rng.integers(0, 8, 3800), rng.integers(0, 20000, 3800), rng.integers(0, 20000, 3800)
    began = time.process_time()
    found = sum(timing.contacts_of(x, y, z, 8) for _ in range(20))
    spent = time.process_time() - began
    at = np.stack([x, y, z], axis=1)
    want = sum(int((((at[i + 1 :] - at[i]) ** 2).sum(axis=1) <= 64).sum()) for i in range(len(at)))
    assert found == 20 * want and want > 0 and spent < 1
    assert timing.contacts_of(x[:0], y[:0], z[:0], 8) == 0


def test_listed_pairs_hold_the_contacts_of_every_step(spark):
    points = spark.sql("select id % 2 as k, pmod(hash(id, 1), 60) + 0L gx, pmod(hash(id, 2), 60) + 0L gy, pmod(hash(id, 3), 90) + 0L gz from range(900)")
    got = {(r.k, r.step): (r.load, r.contacts) for r in timing.timed(points, ["k"], 40).collect()}
    for k, part in points.toPandas().groupby("k"):
        x, y, z = (part[g].to_numpy() for g in ("gx", "gy", "gz"))
        assert all(got[k, s] == (len(part), timing.contacts_of(x, y, np.maximum(z - s, 0), 8)) for s in range(40))

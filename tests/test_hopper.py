"""Contacts of the draining hopper against brute force over every snapshot."""

import numpy as np

from cellbalance import registry
from cellbalance.operators import contacts, sfc
from cellbalance.plans import hopper
from pyspark.sql import functions as F


def brute(points):
    """Positions of the first partner of each pair at most 8 apart, by snapshot."""
    out = {}
    for k, part in points.groupby("snapshot"):
        part = part.sort_values("pid")
        at = part[["gx", "gy", "gz"]].to_numpy()
        near = ((at[:, None] - at[None]) ** 2).sum(axis=2) <= 64
        first, _ = np.nonzero(np.triu(near, 1))
        out[k] = at[first]
    return out


def test_contacts_are_counted_in_every_snapshot(spark, data):
    want = brute(hopper.hopper(spark, data).toPandas())
    got = {r.snapshot: r.contacts for r in registry.QUERIES["hopper_contacts_every_snapshot"](spark, data).collect()}
    assert got == {k: len(want[k]) for k in range(31)}


def test_contact_loads_of_every_snapshot(spark, data):
    want = brute(hopper.hopper(spark, data).toPandas())
    got = {(r.snapshot, r.algo): r for r in registry.QUERIES["hopper_contact_load_series"](spark, data).collect()}
    assert len(got) == 3 * 31
    for k, first in want.items():
        roots = np.unique(first >> 8, axis=0, return_counts=True)[1]
        assert got[k, "static"].max_load == max(roots, default=0)
        assert all(got[k, a].optimum == round(len(first) / hopper.P, 6) and got[k, a].max_load >= got[k, a].optimum for a in ("static", "morton", "hilbert"))


def test_leaves_that_share_a_key_are_cut_alike_in_every_run(spark):
    # 32 cells further along x the curve's key is the same
    rows = [(0, 3, 32 * i, 0, 0, 1 + i * 7 % 11) for i in range(60)]
    got = []
    for some in (rows, rows[::-1], rows[1::2] + rows[::2]):
        leaves = spark.createDataFrame(some, "snapshot int, level int, cx long, cy long, cz long, weight long").coalesce(1)
        placed = sfc.cut_each(sfc.keyed(leaves, hopper.DOM, "hilbert"), "snapshot", "curve_key", 5, 3 * hopper.DOM.key_bits)
        got.append({r.cx: r.rank_id for r in placed.collect()})
    assert got[0] == got[1] == got[2] and len(set(got[0].values())) == 5


def test_counts_by_first_cell_and_by_snapshot_add_up(spark, data):
    points = hopper.hopper(spark, data, [0, 15, 30])
    both = contacts.between_cells(points, 8, 5, occupied=True)
    want = {tuple(r)[:4]: r.n for r in both.groupBy("snapshot", "cx", "cy", "cz").agg(F.sum("contacts").alias("n")).collect()}
    first = contacts.between_cells(points, 8, 5, occupied=True, by="first")
    assert {tuple(r)[:4]: r.n for r in first.groupBy("snapshot", "cx", "cy", "cz").agg(F.sum("contacts").alias("n")).collect()} == want
    none = contacts.between_cells(points, 8, 5, by="none").groupBy("snapshot").agg(F.sum("contacts").alias("n")).collect()
    assert {r.snapshot: r.n for r in none} == {k: sum(n for c, n in want.items() if c[0] == k) for k in (0, 15, 30)}


def test_snapshots_move_one_at_a_time_where_the_table_is_large(spark, data):
    base = hopper.diffusion.written(hopper.particles(spark, data))
    one, all_ = (hopper.contact_pairs(base, by="none", most=most) for most in (1, 1 << 40))
    assert {r.snapshot: r["sum(contacts)"] for r in one.groupBy("snapshot").sum("contacts").collect()} == {r.snapshot: r["sum(contacts)"] for r in all_.groupBy("snapshot").sum("contacts").collect()}

"""Sources, sinks, SQL functions, triggers and the pipeline call."""

import subprocess
import sys

from pyspark.sql import functions as F

from cellbalance.functions import sqlfuncs
from cellbalance.operators import contacts, diffusion, metrics, octree, policy, sfc
from cellbalance.operators.pipeline import RebalanceConfig, rebalance
from cellbalance.plans import wedge
from cellbalance.sources import lattice, layout


def test_lattice_source_reads_what_the_generator_makes(spark):
    spark.dataSource.register(lattice.LatticeSource)
    got = spark.read.format("lattice").option("nx", 4).option("ny", 3).option("nz", 2).load()
    assert got.drop("radius").exceptAll(lattice.cubic(spark, 4, 3, 2).select("pid", "x", "y", "z")).count() == 0 and got.count() == 24


def test_close_packing_has_twelve_contacts(spark):
    pts = lattice.hcp(spark, 6, 6, 6)
    pairs = contacts.touching_spheres(pts, 0.5)
    per = pairs.select(F.explode(F.array("pid_a", "pid_b")).alias("pid")).groupBy("pid").count()
    assert per.agg(F.max("count")).first()[0] == 12
    assert lattice.drop(lattice.cubic(spark, 2, 2, 2).withColumn("vz", F.lit(0.0)), 100).agg(F.min("z")).first()[0] == 0.5


def test_layout_prunes_to_the_box(spark, data, tmp_path):
    b = wedge.half(spark, data)
    asg = diffusion.written(sfc.balance(b.leaves, wedge.DOM, wedge.P))
    layout.write(b.points, asg, wedge.DOM, wedge.P, f"{tmp_path}/rows")
    assert spark.read.parquet(f"{tmp_path}/rows").count() == b.points.count()
    box = layout.read_box(spark, f"{tmp_path}/rows", wedge.DOM, (0, 0, 0), (3, 3, 3), 2)
    inside = b.points.filter("gx < 256 and gy < 256").count()
    assert box.filter("gx < 256 and gy < 256").count() == inside <= box.count() < b.points.count()


def test_pipeline_balances_and_settles(spark, data):
    points, dom = wedge.wedge(spark, data, wedge.HALF), wedge.DOM
    first = rebalance(spark, points, octree.uniform(spark, dom, 1), None, dom, RebalanceConfig(wedge.P))
    before = metrics.max_load(wedge.baselines.one_to_one(octree.weighed(octree.uniform(spark, dom, 1), octree.pyramid(points, dom))), wedge.P).first()
    after = metrics.max_load(first.assignment, wedge.P).first()
    assert after.total == before.total and after.max_load < before.max_load and first.moved.count() > 0
    again = rebalance(spark, points, first.leaves, first.assignment, dom, RebalanceConfig(wedge.P))
    assert again.leaves.exceptAll(first.leaves).count() == 0 and again.moved.count() == 0
    assert set(first.seconds) == {"weights", "adapt", "distribute", "plan"}


def test_triggers():
    assert policy.every(100)(200) and not policy.every(100)(250)
    assert policy.threshold(2.0)(1, max_load=5, mean_load=2) and not policy.threshold(2.0)(1, max_load=4, mean_load=2)
    assert policy.amortized(10, 1)(1, max_load=3, mean_load=1, steps_left=6) and not policy.amortized(10, 1)(1, max_load=3, mean_load=1, steps_left=5)


def test_combined_trigger_and_memory_ranges(spark):
    due = policy.both(policy.every(6), policy.threshold(3.0))
    assert due(12, max_load=7, mean_load=2) and not due(13, max_load=7, mean_load=2) and not due(12, max_load=6, mean_load=2)
    most = {r.algo: r.max_p for r in metrics.max_feasible_p(metrics.memory_model(wedge.process_counts(spark)), metrics.rank_budget()).collect()}
    # as reported: k-way variants end at 4,096 ranks, repartitioning at 8,192, curves later, diffusion nowhere
    assert most["multilevel_kway"] == most["sfc_seeded_kway"] == 4096 < most["unified_repartition"] == 8192 < most["hilbert"] == most["morton"] < most["diffusion"] == 1 << 20


def test_largest_domain_is_refused_beyond_the_ids():
    import pytest

    from cellbalance.operators.domain import Domain

    with pytest.raises(ValueError, match="several domains"):
        Domain((1 << 18, 1, 1), 2)


def test_nearest_seed_matches_brute_force(spark):
    import random

    from cellbalance.operators import related

    rng = random.Random(3)
    pts = list({(rng.randrange(1024), rng.randrange(1024) ** 2 % 1024, rng.randrange(40)) for _ in range(400)}) + [(90_000, 5, 5)]
    seeds = [(i, rng.randrange(1024), rng.randrange(300), rng.randrange(1024)) for i in range(37)] + [(37, 3, 3, 3), (38, 3, 3, 3)]
    points = spark.createDataFrame([(*p, 1) for p in pts], "gx long, gy long, gz long, weight long")
    got = {(r.gx, r.gy, r.gz): r.part_id for r in related.nearest(points, spark.createDataFrame(seeds, "seed long, sx long, sy long, sz long")).collect()}
    want = {p: min(seeds, key=lambda s: (sum((a - b) ** 2 for a, b in zip(p, s[1:])), s[0]))[0] for p in pts}
    assert got == want


def test_sql_functions(spark):
    sqlfuncs.register(spark)
    row = spark.sql("select morton_key(1, 0, 1) m, cell_of(1023, 8) c").first()
    assert (row.m, row.c) == (5, 3)
    assert spark.sql("select count(*) n from octree_children(0, 1, 1, 1)").first().n == 8
    assert spark.sql("select count(*) n from stencil(0, 1, 1, 1, 'face')").first().n == 6


def test_core_imports_without_the_training_data_part():
    code = "import sys; sys.modules['cellbalance.llm'] = None; sys.modules['corpus_pipeline'] = None; import __spark_entry__ as e; q = e.queries(); assert len(q) > 100 and not any(k.startswith('op') and k[2:3].isdigit() for k in q), list(q); assert set(e.oracle_sql()) <= set(q)"
    subprocess.run([sys.executable, "-c", code], check=True, cwd=__file__.rsplit("/tests/", 1)[0])

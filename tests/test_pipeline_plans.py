"""What the pipeline plans: its steps follow from written tables, so no plan holds the leaves over and over."""

from cellbalance.operators import octree, pipeline
from cellbalance.plans import hopper
from pyspark.sql import functions as F


def test_no_step_of_the_pipeline_plans_hundreds_of_tables(spark, data, monkeypatch):
    seen, write = [], pipeline.diffusion.written

    def counted(df):
        seen.append(df._jdf.queryExecution().analyzed().collectLeaves().size())
        return write(df)

    monkeypatch.setattr(pipeline.diffusion, "written", counted)
    points = hopper.hopper(spark, data, [0]).select("gx", "gy", "gz")
    start = octree.uniform(spark, hopper.DOM, 0)
    got = pipeline.rebalance(spark, points, start, None, hopper.DOM, pipeline.RebalanceConfig(hopper.P, factor=2))
    assert max(seen) < 100
    pyr = write(octree.pyramid(points, hopper.DOM))
    raw = write(octree.adapt(octree.weighed(start, pyr), pyr, hopper.DOM, hopper.P, factor=2))
    want = octree.closed_leaves(spark, raw, pyr, hopper.DOM).collect()
    assert sorted(map(tuple, got.leaves.collect())) == sorted(map(tuple, want))


def long_row_of_cells(spark, n):
    """n finest cells along x, most beyond the box: many rows in few bytes."""
    zero = F.lit(0).cast("long")
    return pipeline.diffusion.written(spark.range(n).select(zero.alias("snapshot"), F.lit(3).alias("level"), F.col("id").alias("cx"), zero.alias("cy"), zero.alias("cz"), F.lit(1).cast("long").alias("weight")))


def test_occupied_cells_are_not_broadcast_to_the_leaves(spark):
    found = octree.weighed(octree.uniform(spark, hopper.DOM, 3), long_row_of_cells(spark, 100_000))
    assert sum(r.weight for r in found.collect()) == 32
    assert "Broadcast" not in found._jdf.queryExecution().executedPlan().toString()


def test_loads_under_an_assignment_send_the_leaves_and_not_the_cells(spark):
    asg = octree.uniform(spark, hopper.DOM, 3).withColumn("rank_id", F.col("cx") % 2)
    cells = long_row_of_cells(spark, 100_000)
    held = hopper.held_under(asg, cells)
    assert {r.rank_id: r.load for r in held.collect()} == {0: 16, 1: 16}
    plan = held._jdf.queryExecution().executedPlan().toString()
    assert "BuildRight" in plan and "BuildLeft" not in plan
    assert hopper.loads_under(asg, cells) == [(0, 16, 32)]

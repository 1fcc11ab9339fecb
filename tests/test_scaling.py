"""The log of the weak scaling: no algorithm is left out at a size."""

from cellbalance.plans import scaling
from pyspark.sql import functions as F


def test_every_algorithm_is_timed_at_every_size(spark, data, monkeypatch):
    # which runs are made, not how they balance: everything goes to one rank
    monkeypatch.setattr(scaling, "assigned", lambda b, algo: b.leaves.withColumn("rank_id", F.lit(0).cast("long")))
    monkeypatch.setattr(scaling, "_RUNS", {})
    every = {(algo, p) for algo in scaling.LARGE for p in (128, 256, 512)}
    got = {(r.algo, r.p): r.seconds for r in scaling.balancer_runtime(spark, data).collect()}
    assert set(got) == every and all(s is not None for s in got.values())
    loads = [r for r in scaling.large_weak_scaling(spark, data).collect() if r.algo != "static"]
    assert {(r.algo, r.p) for r in loads} == every and all(r.ratio == r.p for r in loads)
    assert {r.algo for r in scaling.scaling_slope(spark, data).collect()} == set(scaling.LARGE)

"""The three-step pipeline as one call: weights, adaptation, distribution; then what has to move."""

from __future__ import annotations

import time
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellbalance.operators import adjacency, baselines, diffusion, metrics, octree, sfc
from cellbalance.operators.domain import Domain
from cellbalance.operators.octree import CELL


@dataclass(frozen=True)
class RebalanceConfig:
    p: int
    algorithm: str = "hilbert"
    cut: str = "midpoint"
    iters: int = 10
    connectivity: str = "corner"
    closed: bool = True
    weight: str | None = None  # a column of the points; none: each point counts one
    factor: int = 1  # leaves over the mean load divided by this are refined
    max_delta: int = 1


@dataclass
class State:
    leaves: DataFrame
    assignment: DataFrame
    moved: DataFrame
    seconds: dict[str, float]


def inherit(leaves: DataFrame, old: DataFrame, dom: Domain) -> DataFrame:
    """New leaves with the rank of the old leaf they come from: the nearest old ancestor for children,
    the rank that holds most weight below for merged parents."""
    down = leaves.withColumn("l", F.explode(F.expr("sequence(0, level)"))).select(*CELL, "weight", F.col("l").alias("u_level"), *[F.expr(f"shiftright({c}, level - l)").alias(f"u_{c}") for c in CELL[1:]])
    from_above = down.join(old.select(*[F.col(c).alias(f"u_{c}") for c in CELL], "rank_id"), [f"u_{c}" for c in CELL]).select(*CELL, "weight", "rank_id")
    below = old.withColumn("l", F.explode(F.expr("sequence(0, level)"))).filter("l < level").select(F.col("l").cast("int").alias("level"), *[F.expr(f"shiftright({c}, level - l)").alias(c) for c in CELL[1:]], "rank_id", F.col("weight").alias("w"))
    held = below.groupBy(*CELL, "rank_id").agg(F.sum("w").alias("w")).groupBy(*CELL).agg(F.max_by("rank_id", F.struct("w", -F.col("rank_id"))).alias("rank_id"))
    return from_above.union(leaves.join(held, CELL).select(*CELL, "weight", "rank_id"))


def rebalance(spark: SparkSession, points: DataFrame, leaves: DataFrame, asg: DataFrame | None, dom: Domain, cfg: RebalanceConfig) -> State:
    """One run of the pipeline from the present leaves and assignment, with wall seconds per step."""
    seconds, start = {}, time.time()

    def done(step: str, df: DataFrame) -> DataFrame:
        nonlocal start
        df = diffusion.written(df)
        seconds[step], start = time.time() - start, time.time()
        return df

    pyr = done("weights", octree.pyramid(points, dom, F.col(cfg.weight) if cfg.weight else None))
    new = octree.adapt(octree.weighed(leaves.select(*CELL), pyr), pyr, dom, cfg.p, factor=cfg.factor, max_delta=cfg.max_delta)
    if cfg.closed:
        # each step reads the one before several times: unwritten, the leaves stand in one plan some seventy times
        inner = diffusion.written(octree.interior_of(diffusion.written(new), dom))
        inner = diffusion.written(octree.close_two_to_one(inner, dom, cfg.connectivity))
        new = octree.weighed(octree.leaves_of(inner, spark, dom), pyr)
    new = done("adapt", new)
    old = inherit(new, asg if asg is not None else baselines.one_to_one(octree.weighed(leaves.select(*CELL), pyr)), dom)
    if cfg.algorithm == "diffusion":
        balanced = diffusion.balance(old, adjacency.full(new, dom), cfg.p, cfg.iters)
    else:
        balanced = sfc.balance(new, dom, cfg.p, cfg.algorithm, cfg.cut)
    balanced = done("distribute", balanced)
    return State(new, balanced, done("plan", metrics.migration(old, balanced)), seconds)

"""Diffusion balancing: loads flow downhill between neighbouring ranks, whole leaves at a time."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cellbalance.operators.octree import leaf_id
from cellbalance.operators.store import cut_lineage, written  # noqa: F401  callers take them from here


def graph(leaves: DataFrame, pairs: DataFrame) -> DataFrame:
    """Leaf adjacency in both directions, by leaf id."""
    a, b = leaf_id_of("src"), leaf_id_of("dst")
    one = pairs.select(a.alias("leaf"), b.alias("other"))
    return one.union(one.select("other", "leaf"))


def leaf_id_of(end: str):
    level, x, y, z = (F.col(f"{end}_{c}").cast("long") for c in ("level", "x", "y", "z"))
    return F.shiftleft(level, 57) + F.shiftleft(x, 38) + F.shiftleft(y, 19) + z


def rank_loads(state: DataFrame, p: int) -> DataFrame:
    """Load of every rank, idle ones included."""
    ranks = state.sparkSession.range(p).withColumnRenamed("id", "rank_id")
    sums = state.groupBy("rank_id").agg(F.sum("weight").alias("load"))
    return ranks.join(sums, "rank_id", "left").select("rank_id", F.coalesce("load", F.lit(0)).alias("load"))


def rank_edges(state: DataFrame, edges: DataFrame) -> DataFrame:
    """Which ranks hold touching leaves: ordered pairs rank_a, rank_b in both directions."""
    place = state.select("leaf", "rank_id")
    both = edges.join(place.select("leaf", F.col("rank_id").alias("rank_a")), "leaf").join(place.select(F.col("leaf").alias("other"), F.col("rank_id").alias("rank_b")), "other")
    return both.filter("rank_a <> rank_b").select("rank_a", "rank_b").distinct()


def touching(state: DataFrame, edges: DataFrame) -> DataFrame:
    """leaf, weight, rank_a, rank_b, faces: the other ranks that each leaf touches, and how often."""
    ahead = state.select(F.col("leaf").alias("other"), F.col("rank_id").alias("rank_b"))
    both = edges.join(state.select("leaf", "weight", F.col("rank_id").alias("rank_a")), "leaf").join(ahead, "other")
    return both.filter("rank_a <> rank_b").groupBy("leaf", "weight", "rank_a", "rank_b").agg(F.count("*").alias("faces"))


def flows(state: DataFrame, touch: DataFrame, p: int, last: DataFrame | None = None, momentum: float = 0.0) -> DataFrame:
    """Flow along each downhill rank edge: load difference over one plus the larger degree.

    With momentum the previous round's flow adds to the gradient (second-order scheme).
    """
    pairs = touch.select("rank_a", "rank_b").distinct()
    degree = pairs.groupBy("rank_a").agg(F.count("*").alias("degree"))
    held = rank_loads(state, p).join(degree.withColumnRenamed("rank_a", "rank_id"), "rank_id", "left")
    a = held.select(F.col("rank_id").alias("rank_a"), F.col("load").alias("load_a"), F.col("degree").alias("degree_a"))
    b = held.select(F.col("rank_id").alias("rank_b"), F.col("load").alias("load_b"), F.col("degree").alias("degree_b"))
    down = pairs.join(a, "rank_a").join(b, "rank_b").filter("load_a > load_b")
    down = down.withColumn("flow", F.expr("(load_a - load_b) div (1 + greatest(degree_a, degree_b))"))
    if last is not None and momentum:
        before = last.select("rank_a", "rank_b", F.col("flow").alias("_last"))
        down = down.join(before, ["rank_a", "rank_b"], "left").withColumn("flow", F.col("flow") + F.floor(F.coalesce("_last", F.lit(0)) * momentum).cast("long")).drop("_last")
    return down.select("rank_a", "rank_b", "load_a", "load_b", "flow")


def select(touch: DataFrame, flow: DataFrame, direction: str = "push", pick: str = "heavy") -> DataFrame:
    """(leaf, rank_b): leaves that move this round.

    A leaf goes to one rank it touches: the sender's choice (push) is the least loaded one, the
    receiver's (pull) the one with most flow. Per pair leaves are taken by descending weight, or by most
    faces towards the receiver (locality), while their sum stays within the flow; the first may exceed
    it if the receiver stays below the sender. Last, each receiver admits inflow only while it stays
    below the sender's load before the round, so the largest load never grows.
    """
    options = touch.filter("weight > 0").join(flow, ["rank_a", "rank_b"])
    best = (F.col("load_b"), F.col("rank_b")) if direction == "push" else (-F.col("flow"), F.col("rank_b"))
    chosen = options.withColumn("_n", F.row_number().over(Window.partitionBy("leaf").orderBy(*best))).filter("_n = 1").drop("_n")
    first = (F.col("weight").desc(), F.col("leaf")) if pick == "heavy" else (F.col("faces").desc(), F.col("weight").desc(), F.col("leaf"))
    pair = Window.partitionBy("rank_a", "rank_b").orderBy(*first)
    queued = chosen.withColumn("_n", F.row_number().over(pair)).withColumn("_sum", F.sum("weight").over(pair.rowsBetween(Window.unboundedPreceding, 0)))
    queued = queued.filter("_sum <= flow or (_n = 1 and load_b + weight < load_a)")
    arrive = Window.partitionBy("rank_b").orderBy(F.col("flow").desc(), "rank_a", "_n").rowsBetween(Window.unboundedPreceding, 0)
    return queued.withColumn("_in", F.sum("weight").over(arrive)).filter("load_b + _in < load_a").select("leaf", "rank_b")


def step(state: DataFrame, edges: DataFrame, p: int, scheme: str = "first_order", direction: str = "push", pick: str = "heavy", last: DataFrame | None = None, momentum: float = 0.5) -> tuple[DataFrame, DataFrame]:
    """One round over a written state. What touches is written, since flows and moves both follow from it."""
    touch = written(touching(state, edges))
    flow = flows(state, touch, p, last if scheme == "second_order" else None, momentum)
    moves = select(touch, flow, direction, pick)
    moved = state.join(moves, "leaf", "left").select("leaf", *[c for c in state.columns if c not in ("leaf", "rank_id")], F.coalesce("rank_b", "rank_id").alias("rank_id"))
    return moved, flow


def run(state: DataFrame, edges: DataFrame, p: int, iters: int = 10, tol: float | None = None, scheme: str = "first_order", direction: str = "push", pick: str = "heavy") -> DataFrame:
    """state (leaf, weight, rank_id and others) after `iters` rounds over edges (leaf, other, both ways).

    The plan is cut after every round: a written state has a known size and is read by a short plan. With
    `tol` the rounds end once the largest load is within the tolerance of the mean. direction may be `alternate`.
    """
    state, edges, last = written(state), written(edges), None
    for k in range(iters):
        way = ("push", "pull")[k % 2] if direction == "alternate" else direction
        state, last = step(state, edges, p, scheme, way, pick, last)
        if tol is not None or k + 1 < iters:
            state = written(state)
            last = written(last) if scheme == "second_order" else None
        if tol is not None:
            most = rank_loads(state, p).agg(F.max("load"), F.sum("load")).first()
            if most[0] * p <= (1 + tol) * (most[1] or 0):
                break
    return state


def balance(old: DataFrame, pairs: DataFrame, p: int, iters: int = 10, **how) -> DataFrame:
    """Assignment after `iters` rounds from the present one (level, cx, cy, cz, weight, rank_id)."""
    state = old.select(leaf_id().alias("leaf"), "level", "cx", "cy", "cz", "weight", F.col("rank_id").cast("long").alias("rank_id"))
    return run(state, graph(state, pairs), p, iters, **how).select("level", "cx", "cy", "cz", "weight", "rank_id")

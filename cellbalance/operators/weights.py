"""Computational and communication weights of leaves and ranks."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cellbalance.operators.octree import CELL


def particles(located: DataFrame) -> DataFrame:
    """Rows per leaf."""
    return located.groupBy(*CELL).agg(F.count("*").alias("weight"))


def given(df: DataFrame, keys: list[str], expr: str) -> DataFrame:
    """A given weight, summed."""
    return df.groupBy(*keys).agg(F.sum(F.expr(expr)).cast("long").alias("weight"))


def contacts(pairs: DataFrame, located: DataFrame, credit: str = "owner", keys: Sequence[str] = CELL) -> DataFrame:
    """Contacts per leaf: credited to the leaf of the first partner, or to each distinct leaf touched."""
    place = located.select("pid", *keys).hint("merge")  # rows, however few bytes of them are read
    if credit == "owner":
        return pairs.join(place, pairs.pid_a == place.pid).groupBy(*keys).agg(F.count("*").alias("weight"))
    if credit != "both":
        raise ValueError(f"unknown credit {credit}")
    sides = pairs.select("pid_a", "pid_b", F.explode(F.array("pid_a", "pid_b")).alias("pid"))
    return sides.join(place, "pid").select("pid_a", "pid_b", *keys).distinct().groupBy(*keys).agg(F.count("*").alias("weight"))


def estimated_contacts(count: Column, coordination: int = 12) -> Column:
    """Pairs expected from a coordination number: each contact has two partners."""
    return (count * coordination / 2).cast("long")


def interface_area(faces: DataFrame) -> DataFrame:
    """Area per leaf, from both sides of each face."""
    sides = faces.select(F.explode(F.array(*[F.struct(*[F.col(f"{e}_{n}").alias(c) for n, c in zip(("level", "x", "y", "z"), CELL, strict=True)]) for e in ("src", "dst")])).alias("s"), "area")
    return sides.select("s.*", "area").groupBy(*CELL).agg(F.sum("area").alias("area"))


def with_ranks(edges: DataFrame, asg: DataFrame) -> DataFrame:
    """Edges with the ranks of both ends."""
    for e in ("src", "dst"):
        end = asg.select(*[F.col(c).cast("long").alias(f"{e}_{n}") for c, n in zip(CELL, ("level", "x", "y", "z"), strict=True)], F.col("rank_id").alias(f"{e}_rank"))
        edges = edges.join(end, [f"{e}_{n}" for n in ("level", "x", "y", "z")])
    return edges


def comm_per_rank(edges: DataFrame, asg: DataFrame) -> DataFrame:
    """Cut area per rank: only faces between two ranks count, for both."""
    cut = with_ranks(edges, asg).filter("src_rank <> dst_rank")
    return cut.select(F.explode(F.array("src_rank", "dst_rank")).alias("rank_id"), "area").groupBy("rank_id").agg(F.sum("area").alias("comm"))


def measured(log: DataFrame, window: int = 100) -> DataFrame:
    """Weight from timings: the mean of the last `window` steps per leaf."""
    last = log.groupBy(*CELL).agg(F.max("step").alias("_last"))
    recent = log.join(last, CELL).filter(F.col("step") > F.col("_last") - window)
    return recent.groupBy(*CELL).agg(F.avg("value").alias("weight"))

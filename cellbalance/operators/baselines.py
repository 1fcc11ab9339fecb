"""Placements without a balancer: static, round robin, hash, largest first."""

from __future__ import annotations

import heapq

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellbalance.operators.octree import CELL, leaf_id
from cellbalance.operators.sfc import prefix


def numbered(leaves: DataFrame) -> DataFrame:
    """Leaves with `before`, their place in lexicographic cell order."""
    return prefix(leaves.withColumn("_id", leaf_id()).withColumn("_one", F.lit(1).cast("long")), "_id", "_one").drop("_id", "_one")


def one_to_one(leaves: DataFrame) -> DataFrame:
    """The unbalanced start: leaf k of the initial partition belongs to rank k."""
    return numbered(leaves).select(*CELL, "weight", F.col("before").alias("rank_id"))


def round_robin(leaves: DataFrame, p: int) -> DataFrame:
    return numbered(leaves).select(*CELL, "weight", (F.col("before") % p).alias("rank_id"))


def hashed(leaves: DataFrame, p: int) -> DataFrame:
    return leaves.select(*CELL, "weight", F.pmod(F.xxhash64(leaf_id()), F.lit(p)).alias("rank_id"))


def largest_first(leaves: DataFrame, p: int, ranks_a_group: int = 1024) -> DataFrame:
    """Longest-processing-time greedy. Leaves and ranks are dealt into groups of `ranks_a_group` ranks, one
    task each, so what a task holds follows the ranks of its group; up to that many ranks it is the plain
    heuristic."""
    groups = -(-p // ranks_a_group)

    def run(part: pd.DataFrame) -> pd.DataFrame:
        g = int(part["g"].iloc[0])
        heap = [(0, r) for r in range(g, p, groups)]
        part = part.sort_values(["weight", *CELL], ascending=[False, True, True, True, True])
        ranks = []
        for w in part["weight"]:
            load, r = heapq.heappop(heap)
            ranks.append(r)
            heapq.heappush(heap, (load + w, r))
        return part.assign(rank_id=ranks)[[*CELL, "weight", "rank_id"]]

    dealt = leaves.select(*CELL, "weight", F.pmod(F.xxhash64(leaf_id()), F.lit(groups)).alias("g"))
    return dealt.groupBy("g").applyInPandas(run, "level int, cx long, cy long, cz long, weight long, rank_id long")

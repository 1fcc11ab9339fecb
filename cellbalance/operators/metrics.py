"""Quality and cost measures over assignments and measurement logs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cellbalance.operators.diffusion import rank_loads
from cellbalance.operators.octree import CELL
from cellbalance.operators.weights import comm_per_rank, with_ranks


def max_load(asg: DataFrame, p: int) -> DataFrame:
    """max_load, total, mean_load, ratio over all p ranks, idle ones included."""
    loads = rank_loads(asg, p).agg(F.max("load").alias("max_load"), F.sum("load").alias("total"))
    return loads.select("max_load", "total", F.round(F.col("total") / p, 6).alias("mean_load"), F.round(F.expr(f"case when total = 0 then 1.0 else max_load * {p}.0D / total end"), 6).alias("ratio"))


def trailing_mean(value: str, order: str, by: list[str], k: int = 100) -> Column:
    return F.avg(value).over(Window.partitionBy(*by).orderBy(order).rowsBetween(-(k - 1), 0))


def optimum(total: Column, p: int) -> Column:
    return total / p


def gain(before: DataFrame, after: DataFrame) -> DataFrame:
    """Mean step time before over mean step time after."""
    return before.agg(F.avg("value").alias("b")).join(after.agg(F.avg("value").alias("a"))).select(F.round(F.col("b") / F.col("a"), 6).alias("gain"))


def step_time_model(asg: DataFrame, faces: DataFrame, p: int, a: float = 1.0, b: float = 0.0) -> DataFrame:
    """Modelled time of a step: the slowest rank, load and cut area weighed."""
    comm = comm_per_rank(faces, asg)
    both = rank_loads(asg, p).join(comm, "rank_id", "left")
    return both.agg(F.max(F.col("load") * a + F.coalesce("comm", F.lit(0)) * b).alias("step_time"))


def edge_cut(asg: DataFrame, faces: DataFrame) -> DataFrame:
    cut = with_ranks(faces, asg).filter("src_rank <> dst_rank")
    return cut.agg(F.coalesce(F.sum("area"), F.lit(0)).alias("cut_area"), F.count("*").alias("cut_edges"))


def locality(asg: DataFrame, faces: DataFrame) -> DataFrame:
    """Share of faces within a rank, and the mean distance of ranks across the others."""
    ends = with_ranks(faces, asg)
    return ends.agg(
        F.round(F.avg((F.col("src_rank") == F.col("dst_rank")).cast("double")), 6).alias("inside"),
        F.round(F.avg(F.when(F.col("src_rank") != F.col("dst_rank"), F.abs(F.col("src_rank") - F.col("dst_rank")))), 6).alias("rank_distance"),
    )


def fragments(asg: DataFrame, faces: DataFrame) -> DataFrame:
    """Connected pieces of each rank's leaves: least labels spread over faces within ranks."""
    from cellbalance.operators.diffusion import graph
    from cellbalance.operators.octree import leaf_id
    from cellbalance.operators.store import written

    state = asg.select(leaf_id().alias("leaf"), "rank_id")
    inside = with_ranks(faces, asg).filter("src_rank = dst_rank")
    edges = written(graph(asg, inside))
    labels = written(state.select("leaf", "rank_id", F.col("leaf").alias("label")))
    while True:
        near = edges.join(labels.select(F.col("leaf").alias("other"), F.col("label").alias("l")), "other").groupBy("leaf").agg(F.min("l").alias("near"))
        via = labels.join(near, "leaf", "left").select("leaf", "rank_id", F.col("label").alias("old"), F.least("label", F.coalesce("near", "label")).alias("via"))
        nxt = written(via.join(labels.select(F.col("leaf").alias("via"), F.col("label").alias("far")), "via").select("leaf", "rank_id", "old", F.least("via", "far").alias("label")))
        labels = nxt.select("leaf", "rank_id", "label")
        if nxt.filter("label < old").isEmpty():
            return labels.groupBy("rank_id").agg(F.count_distinct("label").alias("fragments"))


def migration(old: DataFrame, new: DataFrame) -> DataFrame:
    """Leaves whose rank differs; leaves present on one side only count as moved."""
    o = old.select(*CELL, F.col("rank_id").alias("old_rank"), F.col("weight").alias("old_weight"))
    n = new.select(*CELL, F.col("rank_id").alias("new_rank"), "weight")
    return o.join(n, CELL, "full").filter(~F.col("old_rank").eqNullSafe(F.col("new_rank"))).select(*CELL, "old_rank", "new_rank", F.coalesce("weight", "old_weight").alias("weight"))


def migration_volume(old: DataFrame, new: DataFrame) -> DataFrame:
    return migration(old, new).agg(F.count("*").alias("moved_leaves"), F.coalesce(F.sum("weight"), F.lit(0)).alias("moved_weight"))


def surface(leaves: DataFrame, deepest: int) -> DataFrame:
    """Summed surface of all leaves in finest-cell units, walls included."""
    side = F.expr(f"shiftleft(cast(1 as bigint), cast(2 * ({deepest} - level) as int))")
    return leaves.agg(F.sum(6 * side).alias("surface"))


def granularity(leaves: DataFrame, p: int) -> DataFrame:
    return leaves.agg(F.max("weight").alias("w_max"), F.round(F.max("weight") * F.lit(float(p)) / F.sum("weight"), 6).alias("granularity"))


#: What a rank must hold of all leaves, in bytes a leaf: a record of 24 for the curves' all-gather; the graph
#: (a record and 26 arcs of 16) once for repartitioning, which starts from the partition at hand, and twice
#: with the coarser levels for the k-way variants. Diffusion holds its own leaves and its neighbours' loads.
RECORD, ARCS = 24, 26 * 16
BYTES_A_LEAF = {"morton": RECORD, "hilbert": RECORD, "multilevel_kway": 2 * (RECORD + ARCS), "sfc_seeded_kway": 2 * (RECORD + ARCS), "unified_repartition": RECORD + ARCS}


def rank_budget(node_bytes: int = 16 << 30, ranks_a_node: int = 64, share: float = 0.125) -> int:
    """Bytes a rank has for balancing: its part of the node's memory, of which particles take the rest."""
    return int(node_bytes / ranks_a_node * share)


def memory_model(ps: DataFrame, leaves_per_rank: int = 8) -> DataFrame:
    """algo, p, bytes per rank and bytes of all ranks: only diffusion's do not grow with p."""
    own = F.lit(leaves_per_rank * RECORD + ARCS).cast("long")
    out = None
    for algo, per in [*((a, F.col("p") * leaves_per_rank * b) for a, b in BYTES_A_LEAF.items()), ("diffusion", own)]:
        row = ps.select(F.lit(algo).alias("algo"), "p", per.cast("long").alias("rank_bytes"), (per.cast("decimal(38,0)") * F.col("p")).cast("decimal(38,0)").alias("all_bytes"))
        out = row if out is None else out.union(row)
    return out


def max_feasible_p(model: DataFrame, budget: int) -> DataFrame:
    return model.filter(F.col("rank_bytes") <= budget).groupBy("algo").agg(F.max("p").alias("max_p"))


def scaling_order(log: DataFrame) -> DataFrame:
    """Slope of time against p on log axes, per algorithm."""
    return log.groupBy("algo").agg(F.round(F.regr_slope(F.ln("seconds"), F.ln("p")), 6).alias("slope"))


def weak_scaling(log: DataFrame) -> DataFrame:
    """Each size against the one before: growth of p and of the largest load, and efficiency against the smallest."""
    w = Window.partitionBy("algo").orderBy("p")
    first = F.first("max_load").over(w)
    return log.select("algo", "p", "max_load", F.lag("max_load").over(w).alias("previous"), F.round(first / F.col("max_load"), 6).alias("efficiency"))


def runtime_series(log: DataFrame, k: int = 100) -> DataFrame:
    """Runtime of the trailing k steps and of all so far."""
    w = Window.partitionBy("algo").orderBy("step")
    return log.select("algo", "step", "value", F.sum("value").over(w.rowsBetween(-(k - 1), 0)).alias("recent"), F.sum("value").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("total"))


def load_time_corr(log: DataFrame) -> DataFrame:
    return log.groupBy("algo").agg(F.round(F.corr("seconds", "max_load"), 6).alias("corr"))


def efficiency(speedup: Column, resources: Column) -> Column:
    return speedup / resources


def pipeline_share(pipeline_seconds: Column, total_seconds: Column) -> Column:
    return pipeline_seconds / total_seconds

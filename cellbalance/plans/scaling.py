"""Weak scaling of the filled boxes: loads, modelled gains and the balancers' own runtimes."""

from __future__ import annotations

import time
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellbalance.catalog import query
from cellbalance.operators import adjacency, baselines, diffusion, metrics, sfc
from cellbalance.operators.domain import Domain
from cellbalance.operators.store import written
from cellbalance.operators.weights import comm_per_rank
from cellbalance.plans import sqltext as q
from cellbalance.plans import wedge
from cellbalance.plans.wedge import DEEP, EIGHTH, HALF, P, Built

SLABS = (1, 2, 4, 8)
MEDIUM = ("hilbert", "diffusion", "sfc_seeded_kway")
LARGE = ("morton", "hilbert", "diffusion", "multilevel_kway", "sfc_seeded_kway", "unified_repartition")
SCHEMA = "algo string, slabs int, p long, max_load long, ratio double, gain_compute double, gain_tenth double, gain_full double, seconds double"


def slabbed(b: Built, s: int) -> Built:
    """s copies of the start and of the leaves along z, in a box s roots longer, with s times the ranks."""
    dom = Domain((4, 4, s), DEEP, (1024, 1024, 1024 * s))

    def copies(df: DataFrame) -> DataFrame:
        k = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(s - 1).cast("long")))
        return written(df.withColumn("_k", k).withColumn("cz", F.col("cz") + F.expr("shiftleft(_k, level)")).drop("_k"))

    return replace(b, start=copies(b.start), leaves=copies(b.leaves), dom=dom, p=P * s)


def assigned(b: Built, algo: str) -> DataFrame:
    if algo in ("morton", "hilbert"):
        return sfc.balance(b.leaves, b.dom, b.p, algo)
    if algo == "diffusion":
        return diffusion.balance(wedge.inherited(b), adjacency.full(b.leaves, b.dom), b.p, 10)
    return wedge.graph_assign(b, algo, b.p)


def step_times(asg: DataFrame, faces: DataFrame, p: int):
    """Largest load, ratio to the mean, and modelled step times that weigh the cut area by 0, 0.1 and 1."""
    both = diffusion.rank_loads(asg, p).join(comm_per_rank(faces, asg), "rank_id", "left").select("load", F.coalesce("comm", F.lit(0)).alias("comm"))
    return both.agg(F.max("load").alias("most"), F.sum("load").alias("total"), *[F.max(F.col("load") + w * F.col("comm")).alias(n) for n, w in (("t0", 0.0), ("t1", 0.1), ("t2", 1.0))]).first()


_RUNS: dict[tuple, str] = {}


def measured(spark: SparkSession, sf_dir: str, limit: int, algos: tuple[str, ...], sizes: tuple[int, ...]) -> DataFrame:
    """A row for each algorithm and size: loads, gains over the static start, wall seconds of the balancer on
    the leaf table. Timed once in an application; the queries that read the log share it."""
    named = (spark.sparkContext.applicationId, sf_dir, limit, algos, sizes)
    if named in _RUNS:
        return spark.read.schema(SCHEMA).parquet(_RUNS[named])
    one, rows = wedge.build(spark, wedge.wedge(spark, sf_dir, limit)), []
    for s in sizes:
        b = slabbed(one, s)
        faces, first = written(adjacency.faces(b.leaves, b.dom)), written(adjacency.faces(b.start, b.dom))
        static = written(baselines.one_to_one(b.start))
        before = step_times(static, first, b.p)
        rows.append(("static", s, b.p, before["most"], before["most"] * b.p / max(before["total"], 1), 1.0, 1.0, 1.0, None))
        for algo in algos:
            start = time.time()
            asg = written(assigned(b, algo))
            seconds = time.time() - start
            after = step_times(asg, faces, b.p)
            gains = [round(before[t] / after[t], 6) if after[t] else None for t in ("t0", "t1", "t2")]
            rows.append((algo, s, b.p, after["most"], after["most"] * b.p / max(after["total"], 1), *gains, seconds))
    out = written(spark.createDataFrame(rows, SCHEMA))
    _RUNS[named] = out.inputFiles()[0].rsplit("/", 1)[0]
    return out


@query("medium_weak_scaling")
def medium_weak_scaling(spark, sf_dir):
    """The box filled to an eighth: Hilbert curve, diffusion and curve-seeded k-way, p = 128 and 256."""
    return measured(spark, sf_dir, EIGHTH, MEDIUM, (1, 2)).drop("seconds")


@query("large_weak_scaling")
def large_weak_scaling(spark, sf_dir):
    """The half-filled box: curves, diffusion and the graph methods at p = 128, 256 and 512."""
    return measured(spark, sf_dir, HALF, LARGE, (1, 2, 4)).drop("seconds")


@query("balancer_runtime")
def balancer_runtime(spark, sf_dir):
    """Wall seconds of each balancer on the leaf tables of the half-filled box."""
    return measured(spark, sf_dir, HALF, LARGE, (1, 2, 4)).filter("algo <> 'static'").select("algo", "p", F.col("seconds"))


@query("scaling_slope")
def scaling_slope(spark, sf_dir):
    """Slope of those seconds against p on log axes, over all sizes for each algorithm."""
    return metrics.scaling_order(balancer_runtime(spark, sf_dir))


@query("parallel_efficiency")
def parallel_efficiency(spark, sf_dir):
    """Seconds of the smallest size over those of each: work and ranks grow alike, so this is speed-up over
    resources."""
    log = balancer_runtime(spark, sf_dir)
    first = log.groupBy("algo").agg(F.min_by("seconds", "p").alias("s0"), F.min("p").alias("p0"))
    grown = F.col("p") / F.col("p0")
    return log.join(first, "algo").select("algo", "p", metrics.efficiency(F.col("s0") * grown / F.col("seconds"), grown).alias("efficiency"))


@query("weak_scaling_efficiency")
def weak_scaling_efficiency(spark, sf_dir):
    """Largest load of each size against the size before and the smallest one."""
    return metrics.weak_scaling(measured(spark, sf_dir, HALF, LARGE, (1, 2, 4)))


def _curves_sql(limit: int) -> str:
    parts = [
        q.wedge(limit),
        f"sizes as (select unnest([{', '.join(map(str, SLABS))}]) s)",
        f"copies as (select s, lv, cx, cy, cz + (k.i << lv) cz, w from leaves, sizes, range(0, {max(SLABS)}) k(i) where k.i < s)",
        q.morton("copies", DEEP, 5, "mk"),
        "narrow as (select * from copies where s <= 4)", q.hilbert("narrow", DEEP, 4, "hk4"),
        "broad as (select * from copies where s > 4)", q.hilbert("broad", DEEP, 5, "hk5"),
        "keys as (select 'morton' algo, s, k, w from mk union all select 'hilbert', s, k, w from hk4 union all select 'hilbert', s, k, w from hk5)",
        "sums as (select *, coalesce(sum(w) over (partition by algo, s order by k rows between unbounded preceding and 1 preceding), 0) b, sum(w) over (partition by algo, s) t from keys)",
        "loads as (select algo, s, least(128 * s - 1, ((2 * b + w) * 128 * s) // (2 * t)) r, sum(w) l from sums group by all)",
        "tops as (select algo, s, max(l) m from loads group by all union all select 'static', s, (select max(w) from n1) from sizes)",
    ]
    return "with " + ",\n".join(parts) + " select algo, cast(s as integer) as slabs, cast(128 * s as bigint) as p, cast(m as bigint) as max_load, round(cast((select max(w) from n1) as double) / m, 6) as gain from tops"


for _name, _limit in (("medium", EIGHTH), ("large", HALF)):

    @query(f"{_name}_weak_scaling_curves", _curves_sql(_limit))
    def curves(spark, sf_dir, limit=_limit):
        """Largest loads of both curves and the static start as the box grows along z, and compute gains."""
        one, out = wedge.build(spark, wedge.wedge(spark, sf_dir, limit)), None
        most = one.start.agg(F.max("weight")).first()[0]
        for s in SLABS:
            b = slabbed(one, s)
            for algo in ("static", "morton", "hilbert"):
                asg = baselines.one_to_one(b.start) if algo == "static" else sfc.balance(b.leaves, b.dom, b.p, algo)
                row = metrics.max_load(asg, b.p).select(F.lit(algo).alias("algo"), F.lit(s).alias("slabs"), F.lit(b.p).cast("long").alias("p"), "max_load", F.round(F.lit(float(most)) / F.col("max_load"), 6).alias("gain"))
                out = row if out is None else out.union(row)
        return out


@query("leaf_sweep")
def leaf_sweep(spark, sf_dir):
    """Leaves alone, no points: both curves up to p = 131,072 and diffusion up to p = 8,192."""
    one, out = wedge.half(spark, sf_dir), None
    for algo, sizes in (("morton", (8, 64, 1024)), ("hilbert", (8, 64, 1024)), ("diffusion", (8, 64))):
        for s in sizes:
            b = slabbed(one, s)
            asg = diffusion.balance(wedge.inherited(b), adjacency.full(b.leaves, b.dom), b.p, 4) if algo == "diffusion" else sfc.balance(b.leaves, b.dom, b.p, algo)
            row = metrics.max_load(asg, b.p).select(F.lit(algo).alias("algo"), F.lit(b.p).cast("long").alias("p"), "max_load", "ratio")
            out = row if out is None else out.union(row)
    return out

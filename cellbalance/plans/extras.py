"""Sweeps, other shapes, lattices, file formats and further streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellbalance.catalog import ORACLES, query, table
from cellbalance.operators import adjacency, contacts, diffusion, metrics, octree, sfc
from cellbalance.plans import sqltext as q
from cellbalance.plans import wedge
from cellbalance.sources import lattice
from cellbalance.streaming import rebalance as streams


@query("weights_ablation", f"with {q.wedge(wedge.HALF)}, {q.hilbert('leaves', wedge.DEEP, wedge.BITS)}, {q.midpoint('keyed', wedge.P)}, cnt as (select w, (row_number() over (order by k) - 1) * {wedge.P} // count(*) over () r from keyed) "
       "select 'weights' as cut, cast(max(l) as bigint) as max_load from (select sum(w) l from asg group by r) union all select 'count', cast(max(l) as bigint) from (select sum(w) l from cnt group by r)")  # fmt: skip
def weights_ablation(spark, sf_dir):
    """The curve cut with weights against the cut that ignores them."""
    leaves = wedge.half(spark, sf_dir).leaves
    parts = [metrics.max_load(sfc.balance(leaves, wedge.DOM, wedge.P, "hilbert", how), wedge.P).select(F.lit(name).alias("cut"), "max_load") for name, how in (("weights", "midpoint"), ("count", "count"))]
    return parts[0].union(parts[1])


@query("granularity_sweep")
def granularity_sweep(spark, sf_dir):
    """Refinement thresholds of the mean load over 1, 2 and 4: smaller leaves, loads closer to the mean."""
    points, out = wedge.wedge(spark, sf_dir, wedge.HALF), None
    pyr = diffusion.written(octree.pyramid(points, wedge.DOM))
    for factor in (1, 2, 4):
        leaves = diffusion.written(octree.adaptive(spark, pyr, wedge.DOM, wedge.P, factor))
        row = metrics.max_load(sfc.balance(leaves, wedge.DOM, wedge.P), wedge.P).join(metrics.granularity(leaves, wedge.P)).select(F.lit(factor).alias("factor"), "max_load", "ratio", "w_max")
        out = row if out is None else out.union(row)
    return out


def _closed_over(kind: str, reach: int) -> str:
    """Leaves counted after closure over neighbours that differ along `reach` axes at most."""
    return f"""select '{kind}' as kind, count(*) as leaves from (with {q.wedge(wedge.EIGHTH)},
inner_k as (select cx, cy, cz from roots where not exists (select 1 from merged m where m.cx = roots.cx and m.cy = roots.cy)
  union select (cx + dx) >> 1, (cy + dy) >> 1, (cz + dz) >> 1 from hot, stencil where abs(dx) + abs(dy) + abs(dz) <= {reach} and cx + dx between 0 and 7 and cy + dy between 0 and 7 and cz + dz between 0 and 1)
select cx from roots where not exists (select 1 from inner_k i where i.cx = roots.cx and i.cy = roots.cy)
union all select n1.cx from n1 join inner_k i on n1.cx >> 1 = i.cx and n1.cy >> 1 = i.cy and n1.cz >> 1 = i.cz where not exists (select 1 from hot h where h.cx = n1.cx and h.cy = n1.cy and h.cz = n1.cz)
union all select 2 * cx from hot, octants)"""


@query("closure_connectivity", " union all ".join(_closed_over(k, n) for k, n in (("face", 1), ("edge", 2), ("corner", 3))))
def closure_connectivity(spark, sf_dir):
    """Leaves after closure over faces, edges and corners."""
    b, out = wedge.build(spark, wedge.wedge(spark, sf_dir, wedge.EIGHTH), kept=True), None
    for kind in ("face", "edge", "corner"):
        row = octree.closed_leaves(spark, b.raw, b.pyr, wedge.DOM, kind).agg(F.lit(kind).alias("kind"), F.count("*").alias("leaves"))
        out = row if out is None else out.union(row)
    return out


_CHECKER = "(gx >> 7) + (gy >> 7) + (gz >> 7)"


@query("checkerboard_loads", f"with {q.CLOUD} select gx >> 7 as cx, gy >> 7 as cy, gz >> 7 as cz, count(*) as weight from cloud where ({_CHECKER}) % 2 = 0 group by all")
def checkerboard(spark, sf_dir):
    cells = wedge.cloud(spark, sf_dir).select(*[F.shiftright(f"g{n}", 7).alias(f"c{n}") for n in "xyz"])
    return cells.filter("(cx + cy + cz) % 2 = 0").groupBy("cx", "cy", "cz").agg(F.count("*").alias("weight"))


@query("half_space_loads", f"with {q.CLOUD} select gx >> 7 as cx, gy >> 7 as cy, gz >> 7 as cz, count(*) as weight from cloud where gz < 512 group by all")
def half_space(spark, sf_dir):
    cells = wedge.cloud(spark, sf_dir).filter("gz < 512").select(*[F.shiftright(f"g{n}", 7).alias(f"c{n}") for n in "xyz"])
    return cells.groupBy("cx", "cy", "cz").agg(F.count("*").alias("weight"))


def part_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A particle for each part: its key says where on a lattice it lies."""
    return table(spark, sf_dir, "part").select(F.col("p_partkey").cast("long").alias("id"))


_STEPS = " union all ".join(f"select a.p_partkey a, b.p_partkey b from part a join part b on b.p_partkey = a.p_partkey + {n}{inside}" for n, inside in ((36, ""), (6, " where a.p_partkey // 6 % 6 < 5"), (1, " where a.p_partkey % 6 < 5")))


@query("cubic_contacts", f"with c as ({_STEPS}), e as (select a pid from c union all select b from c) select pid, count(*) as contacts from e group by pid")
def cubic_contacts(spark, sf_dir):
    pairs = contacts.touching_spheres(lattice.cubic_of(part_ids(spark, sf_dir), 6, 6), 0.5)
    return pairs.select(F.explode(F.array("pid_a", "pid_b")).alias("pid")).groupBy("pid").agg(F.count("*").alias("contacts"))


@query("hcp_contacts")
def hcp_contacts(spark, sf_dir):
    """Contacts per sphere of a close packing, a sphere for each part: twelve inside."""
    pairs = contacts.touching_spheres(lattice.hcp_of(part_ids(spark, sf_dir), 8, 8), 0.5)
    return pairs.select(F.explode(F.array("pid_a", "pid_b")).alias("pid")).groupBy("pid").agg(F.count("*").alias("contacts"))


@query("formats_roundtrip", f"with {q.wedge(wedge.EIGHTH)}, f as (select unnest(['csv', 'json', 'orc', 'parquet']) fmt) select fmt, count(*) as leaves, cast(sum(w) as bigint) as weight from leaves, f group by fmt")
def formats(spark, sf_dir):
    """The leaf table through each file format, with its declared schema."""
    leaves, root, out = wedge.build(spark, wedge.wedge(spark, sf_dir, wedge.EIGHTH), kept=True).leaves, streams.tempfile_dir(spark), None
    for fmt in ("csv", "json", "orc", "parquet"):
        leaves.write.format(fmt).save(f"{root}/{fmt}")
        row = spark.read.format(fmt).schema(leaves.schema).load(f"{root}/{fmt}").agg(F.lit(fmt).alias("fmt"), F.count("*").alias("leaves"), F.sum("weight").alias("weight"))
        out = row if out is None else out.union(row)
    return out


@query("streamed_placed", "select 0 as zero, count(*) as cnt from events")
def streamed_placed(spark, sf_dir):
    """Stream-static join: every event meets exactly one cell of the assignment."""
    leaves = octree.uniform(spark, streams.DOM, 1).withColumn("weight", F.lit(1).cast("long"))
    asg = diffusion.written(sfc.balance(leaves, streams.DOM, 16))
    found = streams.collected(streams.placed(streams.event_stream(spark, f"{sf_dir}/events.parquet*"), asg).select("event_id", "rank_id"), "placed")
    return found.agg(F.lit(0).alias("zero"), F.count("*").alias("cnt"))


@query("streamed_deduplicated", "select count(distinct event_id) as events from events")
def streamed_deduplicated(spark, sf_dir):
    found = streams.collected(streams.deduplicated(streams.event_stream(spark, f"{sf_dir}/events.parquet*")).select("event_id"), "dedup")
    return found.agg(F.count("*").alias("events"))


@query("neighbour_ranks_of_leaves", f"select rank_a, count(*) as partners from ({ORACLES['rank_edges']}) group by rank_a")
def neighbour_ranks(spark, sf_dir):
    """How many other ranks each rank exchanges with: the partners of a next-neighbour scheme."""
    b = wedge.half(spark, sf_dir)
    state = sfc.balance(b.leaves, wedge.DOM, wedge.P).withColumn("leaf", octree.leaf_id())
    return diffusion.rank_edges(state, diffusion.graph(state, adjacency.full(b.leaves, wedge.DOM))).groupBy("rank_a").agg(F.count("*").alias("partners"))

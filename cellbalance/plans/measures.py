"""Weights from logs, inheritance, remapping, the pipeline as one call, and joins and lateness of streams."""

from __future__ import annotations

import time

from pyspark.sql import functions as F

from cellbalance.catalog import query, table
from cellbalance.operators import adjacency, baselines, contacts, diffusion, graphpart, metrics, octree, pipeline, sfc, weights
from cellbalance.operators.octree import CELL
from cellbalance.plans import hopper, wedge
from cellbalance.plans import sqltext as q
from cellbalance.streaming import rebalance as streams

@query(
    "measured_weights",
    f"with log as (select {streams.CELL_SQL}, epoch_us(ts) // 1000000 // 3600 step, count(*) n from events group by all), last as (select cx, cy, cz, max(step) m from log group by all) "
    "select cast(1 as integer) as level, cx, cy, cz, round(avg(cast(n as double)), 6) as weight from log join last using (cx, cy, cz) where step > m - 100 group by cx, cy, cz",
)
def measured_weights(spark, sf_dir):
    """Weights from a log: mean events of the last hundred hours of each cell."""
    ev = table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    log = streams.cells(ev).groupBy(F.lit(1).alias("level"), "cx", "cy", "cz", F.expr("unix_seconds(ts) div 3600").alias("step")).agg(F.count("*").alias("value"))
    return weights.measured(log).withColumn("weight", F.round("weight", 6))


@query(
    "contact_inflation",
    f"with {hopper._pairs(20)}, sides as (select distinct pid_a, pid_b, gx >> 7 cx, gy >> 7 cy, gz >> 7 cz from pairs join cp on cp.pid = pid_a or cp.pid = pid_b), n as (select count(*) c from pairs) "
    "select (select c from n) as contacts, count(*) as with_ghosts, round(cast(count(*) as double) / (select c from n), 6) as ratio from sides",
)
def contact_inflation(spark, sf_dir):
    """Contacts counted on every leaf that holds a partner, ghosts included, over contacts counted once."""
    located, _ = hopper.placed(spark, sf_dir)
    pairs = diffusion.written(contacts.detect(hopper.contact_points(spark, sf_dir), 20))
    both = weights.contacts(pairs, located, "both").agg(F.sum("weight").alias("with_ghosts"))
    once = pairs.agg(F.count("*").alias("contacts"))
    return once.join(both).select("contacts", "with_ghosts", F.round(F.col("with_ghosts") / F.col("contacts"), 6).alias("ratio"))


# --- inheritance, remapping, pieces, the pipeline


@query("inherited_ranks", wedge._diffused(0))
def inherited_ranks(spark, sf_dir):
    """Ranks of the static start carried to the adapted leaves: down to children, up by weight."""
    b = wedge.half(spark, sf_dir)
    return pipeline.inherit(b.leaves, baselines.one_to_one(b.start), wedge.DOM)


@query("pipeline_assignment", f"with {wedge._ranked('hilbert')} select {q.CELL}, cast(w as bigint) as weight, r as rank_id from asg")
def pipeline_assignment(spark, sf_dir):
    """The pipeline as one call from the static start."""
    b = wedge.half(spark, sf_dir)
    return pipeline.rebalance(spark, b.points, b.start, None, wedge.DOM, pipeline.RebalanceConfig(wedge.P)).assignment


@query("pipeline_time")
def pipeline_time(spark, sf_dir):
    """Wall seconds of each pipeline step, and their share of a hundred contact steps and one pipeline."""
    b = wedge.half(spark, sf_dir)
    state = pipeline.rebalance(spark, b.points, b.start, None, wedge.DOM, pipeline.RebalanceConfig(wedge.P))
    start = time.time()
    contacts.detect(hopper.contact_points(spark, sf_dir), 20).write.format("noop").mode("overwrite").save()
    step = time.time() - start
    log = spark.createDataFrame([(k, s) for k, s in state.seconds.items()], "step string, seconds double")
    total = F.lit(sum(state.seconds.values()) + 100 * step)
    return log.withColumn("step_seconds", F.lit(step)).withColumn("share", metrics.pipeline_share(F.col("seconds"), total))


@query("fragments_per_rank")
def fragments_per_rank(spark, sf_dir):
    """Connected pieces of each rank at p = 32: both curves against placement without locality."""
    b, p, out = wedge.half(spark, sf_dir), 32, None
    faces = diffusion.written(adjacency.faces(b.leaves, wedge.DOM))
    for name, asg in (("morton", sfc.balance(b.leaves, wedge.DOM, p, "morton")), ("hilbert", sfc.balance(b.leaves, wedge.DOM, p)), ("round_robin", baselines.round_robin(b.leaves, p))):
        row = metrics.fragments(diffusion.written(asg), faces).withColumn("algo", F.lit(name))
        out = row if out is None else out.union(row)
    return out


@query("remapped_parts")
def remapped_parts(spark, sf_dir):
    """Weight that moves from the Morton to the Hilbert parts, as numbered and relabelled for most overlap."""
    b, p = wedge.half(spark, sf_dir), 32
    v = diffusion.written(b.leaves.select(octree.leaf_id().alias("v"), "weight"))
    old, new = (diffusion.written(wedge.parts_of(sfc.balance(b.leaves, wedge.DOM, p, c))) for c in ("morton", "hilbert"))
    rows = [(n, graphpart.moved_weight(x, old, v)) for n, x in (("numbered", new), ("remapped", graphpart.remap(new, old, v)))]
    return spark.createDataFrame(rows, "labels string, moved_weight long")


# --- streams


@query(
    "streamed_interval_join",
    "select a.event_id as first_id, b.event_id as next_id from events a join events b on a.user_id = b.user_id and a.event_id <> b.event_id and b.ts >= a.ts and b.ts < a.ts + interval 10 minutes",
)
def streamed_interval_join(spark, sf_dir):
    """Stream-stream join: events of a user within ten minutes after one another."""
    one, two = (streams.event_stream(spark, f"{sf_dir}/events.parquet*").select("event_id", "user_id", "ts") for _ in range(2))
    return streams.collected(streams.within(one, two, "10 minutes"), "pairs")


@query(
    "streamed_late_rows",
    "with d as (select *, event_id % 10 part from events), w as (select max(ts) - interval 1 day mark from d where part between 1 and 5) "
    "select count(*) as rows, count(*) filter (part = 0 and date_trunc('day', ts) + interval 1 day <= mark) as late from d, w",
)
def streamed_late_rows(spark, sf_dir):
    """A tenth of the events arrives last: how many rows fall behind the watermark of the others. A batch
    is held against the watermark that its predecessor began with, so the first of three files sets it."""
    root = streams.tempfile_dir(spark)
    ev = table(spark, sf_dir, "events")
    for part, keep in enumerate(("between 1 and 5", "> 5", "= 0")):  # one file a batch, in this order
        ev.filter(f"event_id % 10 {keep}").coalesce(1).write.parquet(f"{root}/in/part={part}")
        time.sleep(1.1)
    stream = streams.event_stream(spark, f"{root}/in/part=*")
    streams.by_batch(streams.windowed_loads(stream), f"{root}/out", "update")
    kept = spark.read.parquet(f"{root}/out").groupBy("started", "cx", "cy", "cz").agg(F.max("weight").alias("weight")).agg(F.sum("weight").alias("kept"))
    return ev.agg(F.count("*").alias("rows")).join(kept).select("rows", (F.col("rows") - F.col("kept")).alias("late"))

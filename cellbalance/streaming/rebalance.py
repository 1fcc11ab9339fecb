"""Streaming rebalance: event-time loads per cell, a hysteresis trigger, and assignments by version.

Counters are kept at the finest cells of a fixed box, so a change of the tree never rewrites state. Each
micro-batch brings the loads of its window; where the largest load under the last version passes the
threshold, times the mean, the leaves are balanced anew, by a curve or by diffusion from the last version,
and written as the next version of the assignment, idempotently by batch id. Every batch leaves a row of
its loads.
"""

from __future__ import annotations

import time
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from cellbalance.catalog import query, table
from cellbalance.operators import adjacency, diffusion, metrics, octree, policy, sfc
from cellbalance.operators.domain import Domain
from cellbalance.operators.octree import CELL
from cellbalance.operators.store import fresh_path, written

DOM = Domain((4, 4, 4), 1)

#: The cell of an event in SQL.
CELL_SQL = ", ".join(
    f"least(greatest({x}, 0), 1023) >> 7 as {c}"
    for c, x in (("cx", "cast(floor(2 * value) as bigint)"), ("cy", "cast(6 * user_id as bigint)"), ("cz", "(epoch_us(ts) // 1000000 - 1704067200) // 2592"))
)


def event_stream(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    """The events as a file stream with a real event time; `path` is a folder or a file pattern."""
    schema = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def cells(events: DataFrame) -> DataFrame:
    """Events with the finest cell they load, on a fixed box."""
    clip = lambda c: F.least(F.greatest(c, F.lit(0).cast("long")), F.lit(1023).cast("long"))
    return events.select(
        "event_id", "ts", clip(F.floor(2 * F.col("value")).cast("long")).alias("gx"), clip((6 * F.col("user_id")).cast("long")).alias("gy"), clip(F.expr("(unix_seconds(ts) - 1704067200) div 2592")).alias("gz")
    ).withColumns({f"c{n}": F.shiftright(f"g{n}", 7) for n in "xyz"})


def windowed_loads(events: DataFrame, late: str = "1 day", width: str = "1 day") -> DataFrame:
    """Loads per cell and window; rows later than the watermark are dropped."""
    found = cells(events).withWatermark("ts", late).groupBy(F.window("ts", width).alias("w"), "cx", "cy", "cz").agg(F.count("*").alias("weight"))
    return found.select(F.expr("unix_seconds(w.start)").alias("started"), "cx", "cy", "cz", "weight")


def deduplicated(events: DataFrame, late: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def placed(events: DataFrame, assignment: DataFrame) -> DataFrame:
    """Stream-static join: each event with the rank of its cell."""
    return cells(events).join(F.broadcast(assignment.filter("level = 1").select("cx", "cy", "cz", "rank_id")), ["cx", "cy", "cz"])


def within(first: DataFrame, then: DataFrame, gap: str, late: str = "1 day") -> DataFrame:
    """Stream-stream interval join: pairs of one user where the second comes at most `gap` after the
    first. Watermarks on both sides bound the rows kept."""
    a = first.withWatermark("ts", late).select(F.col("event_id").alias("first_id"), F.col("user_id").alias("u"), F.col("ts").alias("t"))
    b = then.withWatermark("ts", late).select(F.col("event_id").alias("next_id"), "user_id", "ts")
    return a.join(b, F.expr(f"u = user_id and first_id <> next_id and ts >= t and ts < t + interval {gap}")).select("first_id", "next_id")


def hot_cells(events: DataFrame, high: int, low: int) -> DataFrame:
    """Stateful counter per cell with hysteresis: a row when a cell turns hot (count at least `high` in a
    batch) or cool again (below `low`)."""

    def update(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        total, hot = state.get if state.exists else (0, False)
        n = sum(len(p) for p in parts)
        now = n >= high if not hot else n >= low
        state.update((total + n, now))
        if now != hot:
            yield pd.DataFrame({"cx": [key[0]], "cy": [key[1]], "cz": [key[2]], "total": [total + n], "hot": [now]})

    return cells(events).groupBy("cx", "cy", "cz").applyInPandasWithState(update, "cx long, cy long, cz long, total long, hot boolean", "total long, hot boolean", "append", GroupStateTimeout.NoTimeout)


class Rebalancer:
    """foreachBatch sink: one versioned assignment for the first batch and each later one that passes the
    trigger; `log` holds (batch, largest, mean, rebalanced) of every batch."""

    def __init__(self, root: str, p: int, threshold: float = 2.0, algorithm: str = "hilbert", iters: int = 3):
        self.root, self.p, self.algorithm, self.iters = root, p, algorithm, iters
        self.due = policy.threshold(threshold)

    def last(self, spark: SparkSession, batch_id: int) -> DataFrame | None:
        """The newest assignment before this batch; a replay finds the same one."""
        root = spark._jvm.org.apache.hadoop.fs.Path(f"{self.root}/versions")
        fs = root.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        held = [int(s.getPath().getName().split("=")[1]) for s in fs.listStatus(root)] if fs.exists(root) else []
        before = [v for v in held if v < batch_id]
        return spark.read.parquet(f"{self.root}/versions/version={max(before)}") if before else None

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        # written first: a merge join with the cells keeps the batch's partitions and does not read those that no
        # cell falls into, so their state is not committed and the stream fails
        loads = written(batch.groupBy(F.lit(1).alias("level"), "cx", "cy", "cz").agg(F.sum("weight").alias("weight")))
        leaves = written(octree.weighed(octree.uniform(spark, DOM, 1), loads))
        old = self.last(spark, batch_id)
        if old is not None:
            old = leaves.join(old.select(*CELL, "rank_id"), CELL).select(*CELL, "weight", "rank_id")
        row = metrics.max_load(old if old is not None else sfc.balance(leaves, DOM, self.p, "morton", "count"), self.p).first()
        due = old is None or self.due(batch_id, max_load=row["max_load"], mean_load=row["mean_load"])
        if due:
            if old is not None and self.algorithm == "diffusion":
                new = diffusion.balance(old, adjacency.full(leaves, DOM), self.p, self.iters)
            else:
                new = sfc.balance(leaves, DOM, self.p, "hilbert" if self.algorithm == "diffusion" else self.algorithm)
            # the path names the batch: a replay overwrites the same version
            new.write.mode("overwrite").parquet(f"{self.root}/versions/version={batch_id}")
        log = spark.createDataFrame([(batch_id, row["max_load"], row["mean_load"], due)], "batch long, max_load long, mean_load double, rebalanced boolean")
        log.write.mode("overwrite").parquet(f"{self.root}/log/nth={batch_id}")


def rebalanced_stream(spark: SparkSession, paths: str, root: str, p: int, threshold: float, algorithm: str) -> DataFrame:
    """Run the sink over a stream of files, one file a batch; the log of its batches."""
    stream = cells(event_stream(spark, paths)).groupBy("cx", "cy", "cz").agg(F.count("*").alias("weight"))
    sink = Rebalancer(root, p, threshold, algorithm)
    stream.writeStream.outputMode("complete").option("checkpointLocation", f"{root}/check").trigger(availableNow=True).foreachBatch(sink).start().awaitTermination()
    return spark.read.parquet(f"{root}/log").drop("nth")


def collected(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a bounded stream to its end and return what it wrote, through a folder."""
    spark, root = stream.sparkSession, tempfile_dir(stream.sparkSession)
    writer = stream.writeStream.option("checkpointLocation", f"{root}/{name}-check").trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", f"{root}/{name}").outputMode("append").start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{root}/{name}")
    # complete and update modes have no file sink: the last batch of each key wins in a table by batch
    writer.outputMode(mode).foreachBatch(lambda b, i: b.write.mode("overwrite").parquet(f"{root}/{name}")).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{root}/{name}")


def by_batch(stream: DataFrame, root: str, mode: str) -> None:
    """Run a bounded stream to its end and write every batch under its number."""
    put = lambda b, i: b.write.mode("overwrite").parquet(f"{root}/batch={i}")
    stream.writeStream.outputMode(mode).option("checkpointLocation", f"{root}-check").trigger(availableNow=True).foreachBatch(put).start().awaitTermination()


def tempfile_dir(spark: SparkSession) -> str:
    return fresh_path(spark, "stream")


@query(
    "streamed_daily_loads",
    f"select cast(epoch_us(ts) // 86400000000 * 86400 as bigint) as started, {CELL_SQL}, count(*) as weight from events group by all",
)
def streamed_daily_loads(spark, sf_dir):
    stream = event_stream(spark, f"{sf_dir}/events.parquet*")
    return collected(windowed_loads(stream), "loads", "complete")


@query("streamed_assignment")
def streamed_assignment(spark, sf_dir):
    """The assignment that the last micro-batch wrote."""
    root = tempfile_dir(spark)
    rebalanced_stream(spark, f"{sf_dir}/events.parquet*", f"{root}/assignment", 16, 2.0, "hilbert")
    found = spark.read.parquet(f"{root}/assignment/versions")
    last = found.agg(F.max("version").alias("version"))
    return found.join(F.broadcast(last), "version").drop("version")


def in_four_files(spark: SparkSession, sf_dir: str) -> str:
    """The events by quarter of the value range, a file each, so that the load moves through the box."""
    root, ev = tempfile_dir(spark), table(spark, sf_dir, "events")
    for k in range(4):
        ev.filter(f"cast(floor(value / 125) as int) {'>= 3' if k == 3 else f'= {k}'}").coalesce(1).write.parquet(f"{root}/in/part={k}")
        time.sleep(1.1)  # files come in order of their time
    return f"{root}/in/part=*"


@query("streamed_rebalances")
def streamed_rebalances(spark, sf_dir):
    """Loads and triggers of four batches, balanced by the Hilbert curve and by diffusion, at a threshold of
    1.5 and at one that never fires: curves and diffusion rebalance as the load moves, the other never."""
    paths, out = in_four_files(spark, sf_dir), None
    for name, algorithm, tau in (("hilbert", "hilbert", 1.5), ("diffusion", "diffusion", 1.5), ("never", "hilbert", 1e9)):
        log = rebalanced_stream(spark, paths, f"{tempfile_dir(spark)}/{name}", 16, tau, algorithm).withColumn("algo", F.lit(name))
        out = log if out is None else out.union(log)
    return out


#: In one batch the cells with at least 50 events turn hot.
_HOT = f"select {CELL_SQL}, count(*) as total, true as hot from events group by cx, cy, cz having count(*) >= 50"


@query("streamed_hot_cells", _HOT)
def streamed_hot_cells(spark, sf_dir):
    return collected(hot_cells(event_stream(spark, f"{sf_dir}/events.parquet*"), 50, 10), "hot")


class HotCell(StatefulProcessor):
    """Hysteresis per cell on typed state: a row when a cell turns hot or cool again."""

    def __init__(self, high: int, low: int):
        self.high, self.low = high, low

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("state", "total long, hot boolean")

    def handleInputRows(self, key: tuple, rows: Iterator[pd.DataFrame], timers: object) -> Iterator[pd.DataFrame]:
        total, hot = self.state.get() or (0, False)
        n = sum(len(p) for p in rows)
        now = n >= self.high if not hot else n >= self.low
        self.state.update((total + n, now))
        if now != hot:
            yield pd.DataFrame({"cx": [key[0]], "cy": [key[1]], "cz": [key[2]], "total": [total + n], "hot": [now]})

    def close(self) -> None:
        pass


def hot_cells_typed(events: DataFrame, high: int, low: int) -> DataFrame:
    """hot_cells on transformWithState; the session's state store must be RocksDB when the stream starts."""
    return cells(events).groupBy("cx", "cy", "cz").transformWithStateInPandas(HotCell(high, low), "cx long, cy long, cz long, total long, hot boolean", "append", "none")


_STORE = "spark.sql.streaming.stateStore.providerClass"


@query("streamed_hot_cells_typed", _HOT)
def streamed_hot_cells_typed(spark, sf_dir):
    before = spark.conf.get(_STORE, None)
    spark.conf.set(_STORE, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        return collected(hot_cells_typed(event_stream(spark, f"{sf_dir}/events.parquet*"), 50, 10), "typed")
    finally:
        spark.conf.unset(_STORE) if before is None else spark.conf.set(_STORE, before)

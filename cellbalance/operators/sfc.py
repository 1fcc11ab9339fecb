"""Curve balancing: order leaves along a curve, cut the order into runs of equal weight."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cellbalance.functions.curves import hilbert_key, morton_key
from cellbalance.operators.domain import Domain
from cellbalance.operators.octree import CELL
from cellbalance.operators.store import written

CURVES = {"morton": morton_key, "hilbert": hilbert_key}


def keyed(leaves: DataFrame, dom: Domain, curve: str = "hilbert", root_order: str = "curve") -> DataFrame:
    """Leaves with curve_key: the key of the lower corner, with the bits below the leaf cleared. The curve
    runs through the grid of roots as well, or (root_order `lexicographic`) through each root by itself,
    roots taken in order of x, y, z."""
    if root_order not in ("curve", "lexicographic"):
        raise ValueError(f"unknown root order {root_order}")
    corner = [F.expr(f"shiftleft({c}, cast({dom.max_level} - level as int))") for c in CELL[1:]]
    low = F.expr(f"cast(3 * ({dom.max_level} - level) as int)")
    if root_order == "curve":
        key = CURVES[curve](*corner, dom.key_bits)
    else:
        inside = [F.pmod(c, F.lit(1 << dom.max_level)).cast("long") for c in corner]
        root = [F.shiftright(c, dom.max_level) for c in corner]
        nth = (root[0] * dom.roots[1] + root[1]) * dom.roots[2] + root[2]
        key = F.shiftleft(nth, 3 * dom.max_level) + (CURVES[curve](*inside, dom.max_level) if dom.max_level else F.lit(0))
    return leaves.withColumn("_key", key).withColumn("curve_key", F.call_function("shiftleft", F.call_function("shiftright", "_key", low), low)).drop("_key")


def prefix(df: DataFrame, order: str, weight: str, ties: tuple[str, ...] = ()) -> DataFrame:
    """df with `before`, the weight in front of each row, and `total`; rows of equal keys in order of `ties`.

    Two levels: rows are dealt into ranges of the order key whose bounds are sampled, so that ranges hold
    like numbers of rows however the keys cluster, and written with the number of their range. The sums of
    the ranges, one row a task, are added up and broadcast back; rows add up inside their own range, so no
    task sees the whole order.
    """
    ranged = written(df.repartitionByRange(order).withColumn("_range", F.spark_partition_id()))
    sums = ranged.groupBy("_range").agg(F.sum(weight).alias("_sum"))
    w = Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sums.select("_range", F.coalesce(F.sum("_sum").over(w), F.lit(0)).alias("_offset"), F.sum("_sum").over(Window.partitionBy()).alias("total"))
    inside = Window.partitionBy("_range").orderBy(order, *ties).rowsBetween(Window.unboundedPreceding, -1)
    ranked = ranged.withColumn("_own", F.coalesce(F.sum(weight).over(inside), F.lit(0)))
    return ranked.join(F.broadcast(offsets), "_range").withColumn("before", F.col("_own") + F.col("_offset")).drop("_range", "_own", "_offset")


def midpoint_rank(p: int) -> str:
    """The run in which the middle of a row's weight falls; decimal, since the product passes 63 bits at scale."""
    d = "cast({} as decimal(38,0))".format
    return f"cast(case when total = 0 then 0 else least({p - 1}, ((2 * {d('before')} + weight) * {p}) div (2 * {d('total')})) end as bigint)"


def cut(ordered: DataFrame, order: str, p: int, how: str = "midpoint") -> DataFrame:
    """ordered (with weight) with rank_id. how: midpoint, count (weights ignored), greedy or optimal."""
    if how == "midpoint":
        return prefix(ordered, order, "weight").withColumn("rank_id", F.expr(midpoint_rank(p))).drop("before", "total")
    if how == "count":
        numbered = prefix(ordered.withColumn("_one", F.lit(1).cast("long")), order, "_one")
        return numbered.withColumn("rank_id", F.expr(f"cast(cast(before as decimal(38,0)) * {p} div total as bigint)")).drop("before", "total", "_one")
    if how not in ("greedy", "optimal"):
        raise ValueError(f"unknown cut {how}")
    rows = written(ordered)
    limit = least_capacity(rows, order, p) if how == "optimal" else None
    starts = run_starts(rows, order, p, limit).withColumn("_start", F.lit(1).cast("long"))
    flagged = rows.join(starts, order, "left").withColumn("_start", F.coalesce("_start", F.lit(0).cast("long")))
    return prefix(flagged, order, "_start").withColumn("rank_id", F.col("before") + F.col("_start") - 1).drop("before", "total", "_start")


def _in_order(rows: DataFrame, order: str) -> DataFrame:
    """Keys and weights in order through one task, which reads them as a stream: leaves, not rows."""
    return rows.select(F.col(order).cast("long").alias(order), F.col("weight").cast("long").alias("weight")).repartition(1).sortWithinPartitions(order)


def run_starts(rows: DataFrame, order: str, p: int, limit: int | None = None) -> DataFrame:
    """Order keys at which the runs start: each run takes rows up to a load of `limit`, or (greedy) up to
    the mean of what is left. One stream over keys and weights holds a batch at a time; the starts stay a
    table."""
    total = rows.agg(F.coalesce(F.sum("weight"), F.lit(0))).first()[0]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen, done, begun = 0, 0, 0  # weight read, weight of closed runs, runs begun
        for batch in batches:
            keys, found = batch.column(0).to_numpy(), []
            ends = seen + np.cumsum(batch.column(1).to_numpy())
            if not len(keys):
                continue
            at = 0
            if not begun:
                found, begun, at = [keys[0]], 1, 1
            while begun < p:
                aim = limit if limit is not None else -(-(total - done) // (p - begun + 1))
                j = max(at, int(np.searchsorted(ends, done + aim, "right")))
                if j >= len(keys):
                    break
                done = int(ends[j - 1]) if j else seen
                found.append(keys[j])
                begun, at = begun + 1, j + 1
            seen = int(ends[-1])
            yield pa.RecordBatch.from_arrays([pa.array(found, pa.int64())], names=[order])

    return _in_order(rows, order).mapInArrow(run, f"{order} long")


def runs_needed(rows: DataFrame, order: str, limits: list[int]) -> dict[int, int]:
    """How many runs each load limit needs, all limits in one stream over keys and weights."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        most, seen = np.array(limits, np.int64), 0
        done, begun = np.zeros(len(most), np.int64), np.ones(len(most), np.int64)
        for batch in batches:
            ends = seen + np.cumsum(batch.column(1).to_numpy())
            if not len(ends):
                continue
            while True:
                j = np.searchsorted(ends, done + most, "right")
                live = j < len(ends)
                if not live.any():
                    break
                done = np.where(live, np.where(j > 0, ends[np.minimum(j, len(ends) - 1) - 1], seen), done)
                begun += live
            seen = int(ends[-1])
        yield pa.RecordBatch.from_arrays([pa.array(most), pa.array(begun)], names=["most", "runs"])

    return {r["most"]: r["runs"] for r in _in_order(rows, order).mapInArrow(run, "most long, runs long").collect()}


def least_capacity(rows: DataFrame, order: str, p: int, probes: int = 32) -> int:
    """The least largest load of p contiguous runs: each round tries `probes` loads between the bounds."""
    row = rows.agg(F.coalesce(F.max("weight"), F.lit(0)), F.coalesce(F.sum("weight"), F.lit(0))).first()
    low = max(row[0], -(-row[1] // p))
    high = low + row[0]  # always enough
    while low < high:
        tried = sorted({low + (high - 1 - low) * k // (probes - 1) for k in range(probes)})
        runs = runs_needed(rows, order, tried)
        fits = [x for x in tried if runs[x] <= p]
        misses = [x for x in tried if runs[x] > p]
        high = min([high, *fits])
        low = max([low, *(x + 1 for x in misses)])
    return low


def balance(leaves: DataFrame, dom: Domain, p: int, curve: str = "hilbert", how: str = "midpoint", root_order: str = "curve") -> DataFrame:
    """level, cx, cy, cz, weight, rank_id."""
    return cut(keyed(leaves, dom, curve, root_order), "curve_key", p, how).select(*CELL, "weight", "rank_id")


def cut_each(ordered: DataFrame, by: str, order: str, p: int, bits: int) -> DataFrame:
    """The midpoint cut of many orders at once, one for each value of `by` (a small non-negative number):
    `by` stands above the `bits` bits of the key, so that a large order is dealt over several tasks. Leaves
    beyond the box may share a key: they come in order of their cells, so every run cuts alike."""
    key = F.shiftleft(F.col(by).cast("long"), bits) + F.col(order)
    ties = tuple(c for c in CELL if c in ordered.columns)
    placed = prefix(ordered.withColumn("_both", key), "_both", "weight", ties).drop("total")
    sums = placed.groupBy(by).agg(F.min("before").alias("_first"), F.sum("weight").alias("total"))
    own = placed.join(sums, by).withColumn("before", F.col("before") - F.col("_first"))
    return own.withColumn("rank_id", F.expr(midpoint_rank(p))).drop("before", "_first", "_both")


def ranges_for_box(dom: Domain, low: tuple[int, int, int], high: tuple[int, int, int], level: int, curve: str = "morton") -> list[tuple[int, int]]:
    """Runs of curve keys that cover a box of level cells, for pruning a layout sorted by key. The walk goes
    down the tree and stops at nodes that lie inside the box, so its length follows the box's surface."""
    from cellbalance.functions.curves import hilbert_index

    bits, top = dom.key_bits, dom.max_level - level
    lows, highs = [v << top for v in low], [(v + 1) << top for v in high]

    def key(corner: tuple[int, ...], side: int) -> int:
        if curve == "hilbert":
            return hilbert_index(corner, bits) >> (3 * side) << (3 * side)
        return sum(((v >> b) & 1) << (3 * b + 2 - i) for b in range(bits) for i, v in enumerate(corner))

    found: list[tuple[int, int]] = []
    todo = [((0, 0, 0), bits)]
    while todo:
        corner, side = todo.pop()
        ends = [c + (1 << side) for c in corner]
        if any(e <= lo or c >= hi for c, e, lo, hi in zip(corner, ends, lows, highs, strict=True)):
            continue
        if side <= top or all(c >= lo and e <= hi for c, e, lo, hi in zip(corner, ends, lows, highs, strict=True)):
            found.append((key(corner, side), key(corner, side) + (1 << (3 * side))))
            continue
        half = side - 1
        todo += [(tuple(c + (((o >> (2 - i)) & 1) << half) for i, c in enumerate(corner)), half) for o in range(8)]
    out: list[tuple[int, int]] = []
    for a, b in sorted(found):
        if out and out[-1][1] >= a:
            out[-1] = (out[-1][0], max(out[-1][1], b))
        else:
            out.append((a, b))
    return out

"""Related decompositions: bisection, kd-tree, multi-sectioning, Voronoi cells, deformed planes."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cellbalance.operators.store import written

AXES = ("gx", "gy", "gz")


def columns_of(points: DataFrame) -> DataFrame:
    """Rows to weighted lattice cells (gx, gy, gz, weight): rows collapse map-side first."""
    return points.groupBy(*AXES).agg(F.count("*").alias("weight"))


def _split(cells: DataFrame, axis: str, k: int) -> DataFrame:
    """Each part cut into k slabs of near equal weight along an axis; equal coordinates stay together.
    Sums run over the distinct coordinates of a part, at most the lattice side of them."""
    sums = cells.groupBy("part_id", axis).agg(F.sum("weight").alias("_w"))
    w = Window.partitionBy("part_id").orderBy(axis)
    placed = sums.withColumn("_before", F.coalesce(F.sum("_w").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    placed = placed.withColumn("_total", F.sum("_w").over(Window.partitionBy("part_id")))
    slab = placed.select("part_id", axis, F.expr(f"least({k - 1}, ((2 * _before + _w) * {k}) div (2 * _total))").cast("long").alias("_slab"))
    return cells.join(slab, ["part_id", axis]).withColumn("part_id", F.col("part_id") * k + F.col("_slab")).drop("_slab")


def rcb(cells: DataFrame, levels: int, axis: str = "cycle") -> DataFrame:
    """Recursive bisection into 2^levels parts at weighted medians: axes in turn, or each round the axis
    along which the cells spread most (orthogonal bisection)."""
    out = written(cells.withColumn("part_id", F.lit(0).cast("long")))
    for k in range(levels):
        if axis == "cycle":
            out = _split(out, AXES[k % 3], 2)
            continue
        spread = out.groupBy("part_id").agg(*[(F.max(a) - F.min(a)).alias(f"_{a}") for a in AXES])
        longest = F.when((F.col("_gx") >= F.col("_gy")) & (F.col("_gx") >= F.col("_gz")), 0).when(F.col("_gy") >= F.col("_gz"), 1).otherwise(2)
        turned = out.join(spread.select("part_id", longest.alias("_axis")), "part_id")
        turned = turned.withColumn("_along", F.when(F.col("_axis") == 0, F.col("gx")).when(F.col("_axis") == 1, F.col("gy")).otherwise(F.col("gz")))
        out = written(_split(turned, "_along", 2).drop("_along", "_axis"))  # read twice by the next round
    return out


def multisection(cells: DataFrame, slabs: tuple[int, int, int]) -> DataFrame:
    """k slabs per axis, each axis inside the slabs of the one before. Weights may be counts or times."""
    out = cells.withColumn("part_id", F.lit(0).cast("long"))
    for axis, k in zip(AXES, slabs, strict=True):
        out = _split(out, axis, k)
    return out


def kdtree(cells: DataFrame, levels: int, face: float = 0.1) -> DataFrame:
    """Bisection that weighs imbalance against the occupied cells cut: per part the axis of least cost."""
    out = written(cells.withColumn("part_id", F.lit(0).cast("long")))
    for _ in range(levels):
        best = None
        for i, axis in enumerate(AXES):
            sums = out.groupBy("part_id", axis).agg(F.sum("weight").alias("_w"), F.count("*").alias("_n"))
            w = Window.partitionBy("part_id").orderBy(axis)
            t = sums.withColumn("_low", F.sum("_w").over(w)).withColumn("_all", F.sum("_w").over(Window.partitionBy("part_id")))
            t = t.select("part_id", F.lit(i).alias("_axis"), F.col(axis).alias("_at"), (F.abs(2 * F.col("_low") - F.col("_all")) + face * F.col("_n")).alias("_cost"))
            best = t if best is None else best.union(t)
        choice = best.groupBy("part_id").agg(F.min_by(F.struct("_axis", "_at"), F.struct("_cost", "_axis", "_at")).alias("c")).select("part_id", "c.*")
        along = F.when(F.col("_axis") == 0, F.col("gx")).when(F.col("_axis") == 1, F.col("gy")).otherwise(F.col("gz"))
        out = written(out.join(choice, "part_id").withColumn("part_id", F.col("part_id") * 2 + (along > F.col("_at")).cast("long")).drop("_axis", "_at"))
    return out


def nearest(points: DataFrame, seeds: DataFrame) -> DataFrame:
    """points (gx, gy, gz, weight) with part_id of the nearest seed (seed, sx, sy, sz); ties go to the
    smaller seed. Seeds lie in grid cells; a point probes the 27 cells around it and is done once the best
    distance is at most the cell's side. The others meet the next grid, with cells twice as wide, until one
    cell holds every seed; no point meets all seeds but for the last grid."""
    seeds = written(seeds.select("seed", *[F.col(s).cast("long").alias(s) for s in ("sx", "sy", "sz")]))
    box = seeds.agg(F.count("*"), *[f(s) for s in ("sx", "sy", "sz") for f in (F.min, F.max)]).first()
    if not box[0]:
        return points.select(*AXES, "weight", F.lit(None).cast("long").alias("part_id")).limit(0)
    widest = max(box[2] - box[1], box[4] - box[3], box[6] - box[5], 1)
    shift = max(0, int(widest / max(1.0, box[0] ** (1 / 3))).bit_length())
    last = widest.bit_length() + 1
    steps = F.array(*[F.struct(*[F.lit(v).cast("long").alias(n) for v, n in zip((x, y, z), "xyz", strict=True)]) for x in (-1, 0, 1) for y in (-1, 0, 1) for z in (-1, 0, 1)])
    left, found = written(points.select(*AXES, "weight")), None
    while True:
        held = seeds.select("seed", "sx", "sy", "sz", *[F.shiftright(s, shift).alias(f"b{s[1]}") for s in ("sx", "sy", "sz")])
        if shift >= last:  # few cells: every seed lies in a cell that any point of the box probes
            held = held.withColumns({f"b{n}": F.lit(0).cast("long") for n in "xyz"})
        cells = left.withColumn("s", F.explode(steps)) if shift < last else left
        at = [(F.shiftright(g, shift) + F.col(f"s.{g[1]}")).alias(f"b{g[1]}") if shift < last else F.lit(0).cast("long").alias(f"b{g[1]}") for g in AXES]
        apart = sum(((F.col(g) - F.col(s)) * (F.col(g) - F.col(s)) for g, s in zip(AXES, ("sx", "sy", "sz"), strict=True)), F.lit(0).cast("long"))
        best = cells.select(*AXES, "weight", *at).join(held, ["bx", "by", "bz"]).groupBy(*AXES, "weight").agg(F.min(F.struct(apart.alias("d"), "seed")).alias("best"))
        here = best.filter(f"best.d <= {1 << (2 * min(shift, 31))}") if shift < last else best
        here = written(here.select(*AXES, "weight", F.col("best.seed").alias("part_id")))
        found = here if found is None else found.union(here)
        left = written(left.join(here.select(*AXES, "weight"), [*AXES, "weight"], "left_anti"))
        if left.isEmpty():
            return found
        shift = min(shift + 1, last)


def voronoi(points: DataFrame, seeds: DataFrame, iters: int = 0) -> DataFrame:
    """Cells of the nearest seed; each iteration moves the seeds to the weighted centres of their cells."""
    for k in range(iters + 1):
        found = nearest(points, seeds)
        if k == iters:
            return found
        seeds = found.groupBy(F.col("part_id").alias("seed")).agg(*[F.floor(F.sum(F.col(g) * F.col("weight")) / F.sum("weight")).cast("long").alias(s) for g, s in zip(AXES, ("sx", "sy", "sz"), strict=True)])
    raise AssertionError


def deform(cells: DataFrame, planes: list[int], axis: str, iters: int = 8, step: float = 0.5) -> list[int]:
    """Shift the inner planes of a slab partition towards the heavier side until loads settle: each
    plane moves by a share of the slab it shrinks, driven by the loads beside it."""
    hist = {r[axis]: r["w"] for r in cells.groupBy(axis).agg(F.sum("weight").alias("w")).collect()}
    planes = list(planes)
    for _ in range(iters):
        edges = [min(hist, default=0), *planes, max(hist, default=0) + 1]
        loads = [sum(w for g, w in hist.items() if a <= g < b) for a, b in zip(edges, edges[1:])]
        for i in range(len(planes)):
            left, right = loads[i], loads[i + 1]
            if left + right:
                share = step * (right - left) / (left + right)
                room = edges[i + 2] - planes[i] if share > 0 else planes[i] - edges[i]
                planes[i] = min(max(planes[i] + int(share * room), edges[i] + 1), edges[i + 2] - 1)
        planes.sort()
    return planes

"""Contacts and ghosts by grid buckets: an equality join on cells plus an exact distance."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellbalance.operators.domain import Domain
from cellbalance.operators.octree import CELL, neighbours

AXES = ("gx", "gy", "gz")


def detect(points: DataFrame, distance: int) -> DataFrame:
    """Pairs (pid_a < pid_b) at most `distance` apart, in lattice units.

    Buckets have the distance as side. One side of the join is spread over its own bucket and half of
    the 26 around it, so every pair meets in exactly one place. Both sides are rows: sorted and merged, since
    Spark takes the few columns read of a large table for small enough to broadcast.
    """
    half = [(x, y, z) for x in (-1, 0, 1) for y in (-1, 0, 1) for z in (-1, 0, 1) if (x, y, z) >= (0, 0, 0)]
    steps = F.array(*[F.struct(*[F.lit(v).cast("long").alias(n) for v, n in zip(s, "xyz", strict=True)]) for s in half])
    cells = points.select("pid", *AXES, *[F.floor(F.col(a) / distance).cast("long").alias(f"b{a}") for a in AXES])
    near = cells.withColumn("s", F.explode(steps)).select("pid", *AXES, *[(F.col(f"b{a}") + F.col(f"s.{a[1]}")).alias(f"b{a}") for a in AXES], ((F.col("s.x") == 0) & (F.col("s.y") == 0) & (F.col("s.z") == 0)).alias("own"))
    a = near.select(F.col("pid").alias("p"), "own", *[F.col(x).alias(f"{x}_a") for x in AXES], *[f"b{x}" for x in AXES])
    b = cells.select(F.col("pid").alias("q"), *[F.col(x).alias(f"{x}_b") for x in AXES], *[f"b{x}" for x in AXES])
    apart = sum(((F.col(f"{x}_a") - F.col(f"{x}_b")) * (F.col(f"{x}_a") - F.col(f"{x}_b")) for x in AXES), F.lit(0).cast("long"))
    found = a.join(b.hint("merge"), [f"b{x}" for x in AXES]).filter((~F.col("own")) | (F.col("p") < F.col("q"))).filter(apart <= distance * distance)
    return found.select(F.least("p", "q").alias("pid_a"), F.greatest("p", "q").alias("pid_b"))


def near_pairs(group: np.ndarray, x: np.ndarray, y: np.ndarray, z: np.ndarray, distance: int, at_once: int = 1 << 21) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs of one group at most `distance` apart, each once, some millions of candidates at a time.

    Points are put in order of group, column of the distance as side, and height; a point meets its own
    column from itself on and half of the eight around it, each in one run of heights.
    """
    if not len(x):
        return
    bx, by, low = x // distance, y // distance, z - z.min()
    bx, by = bx - bx.min() + 1, by - by.min() + 1
    tall, wide = int(low.max()) + 2 * distance + 2, int(by.max()) + 2
    key = ((group * (int(bx.max()) + 2) + bx) * wide + by) * tall + low + distance
    order = np.argsort(key, kind="stable")
    key, x, y, z = key[order], x[order], y[order], z[order]
    for column in (0, 1, wide - 1, wide, wide + 1):
        first = np.searchsorted(key, key + (column * tall - distance), "left") if column else np.arange(1, len(key) + 1)
        held = np.searchsorted(key, key + (column * tall + distance), "right") - first
        ends, begin = np.cumsum(held), 0
        while begin < len(key):
            end = max(begin + 1, int(np.searchsorted(ends, (ends[begin - 1] if begin else 0) + at_once, "right")))
            n = held[begin:end]
            a = np.repeat(np.arange(begin, end), n)
            b = np.arange(len(a)) + np.repeat(first[begin:end] - (np.cumsum(n) - n), n)
            close = (x[a] - x[b]) ** 2 + (y[a] - y[b]) ** 2 + (z[a] - z[b]) ** 2 <= distance * distance
            yield order[a[close]], order[b[close]]
            begin = end


def numbered(*columns: np.ndarray) -> np.ndarray:
    """A number from 0 for each different row of the columns."""
    code = np.zeros(len(columns[0]), np.int64)
    for c in columns:
        low = c - c.min()
        code = np.unique(code * (int(low.max()) + 1) + low, return_inverse=True)[1]
    return code


def between_cells(points: DataFrame, distance: int, shift: int, occupied: bool = False, slab: int = 128, by: str = "both") -> DataFrame:
    """Contacts of each snapshot by the cells (of side 2^shift) of both partners: snapshot, cx, cy, cz of the
    partner with the smaller pid, ox, oy, oz of the other, contacts. Parts of a count may lie in several rows.
    With `occupied` every cell that holds a point has a row, with 0 if need be. `by`: the counts stand by both
    cells, by the `first` (no ox, oy, oz) or by `none` (snapshot and contacts only), which makes less to write.

    Points are dealt into slabs along x; those near the lower side of a slab go to the slab before as well.
    So a point moves once or a little more, and pairs are counted where they are found and not moved at all.
    """
    own = points.withColumn("slab", F.floor(F.col("gx") / slab).cast("long"))
    both = F.when(F.col("gx") - F.col("slab") * slab < distance, F.array("slab", F.col("slab") - 1)).otherwise(F.array("slab"))
    dealt = own.select("snapshot", "pid", *AXES, F.explode(both).alias("slab")).select(F.col("snapshot").cast("long").alias("snapshot"), "pid", *AXES, "slab")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        k, pid, x, y, z, at = (np.concatenate([b.column(i).to_numpy() for b in held]) for i in range(6))
        mine = x // slab == at
        which = numbered(k, x >> shift, y >> shift, z >> shift)
        first = np.unique(which, return_index=True)[1]
        cell, size = np.stack([k[first], x[first] >> shift, y[first] >> shift, z[first] >> shift]), len(first)
        other = size if by == "both" else 1
        ids = [np.unique(which[mine]) * (other + (by == "both"))] if occupied else [np.zeros(0, np.int64)]
        sums = [np.zeros(len(ids[0]), np.int64)]
        for a, b in near_pairs(numbered(k, at), x, y, z, distance):
            a, b = a[w := mine[a] | mine[b]], b[w]
            a, b = np.where(pid[a] < pid[b], a, b), np.where(pid[a] < pid[b], b, a)
            found, n = np.unique(which[a] * other + (which[b] if by == "both" else 0), return_counts=True)
            ids.append(found)
            sums.append(n)
        found, at = np.unique(np.concatenate(ids), return_inverse=True)
        n = np.bincount(at.reshape(-1), np.concatenate(sums), len(found)).astype(np.int64)
        a, b = cell[:, found // other], cell[:, found % other]
        if by == "none":
            ks, at = np.unique(a[0], return_inverse=True)
            a, n = [ks], np.bincount(at.reshape(-1), n, len(ks)).astype(np.int64)
        for i in range(0, len(n), 1 << 16):
            part = slice(i, i + (1 << 16))
            yield pa.RecordBatch.from_arrays([pa.array(v[part]) for v in (*a, *(b[1:] if by == "both" else ()), n)], names=names)

    names = {"both": ["snapshot", "cx", "cy", "cz", "ox", "oy", "oz", "contacts"], "first": ["snapshot", "cx", "cy", "cz", "contacts"], "none": ["snapshot", "contacts"]}[by]
    return dealt.repartition("snapshot", "slab").mapInArrow(run, ", ".join(f"{c} long" for c in names))


def brute_force(points: DataFrame, distance: int) -> DataFrame:
    """The same pairs by a theta join: the reference for small inputs."""
    a, b = (points.select(F.col("pid").alias(f"pid_{s}"), *[F.col(x).alias(f"{x}_{s}") for x in AXES]) for s in "ab")
    apart = sum(((F.col(f"{x}_a") - F.col(f"{x}_b")) * (F.col(f"{x}_a") - F.col(f"{x}_b")) for x in AXES), F.lit(0).cast("long"))
    return a.join(b, (F.col("pid_a") < F.col("pid_b")) & (apart <= distance * distance)).select("pid_a", "pid_b")


def touching_spheres(points: DataFrame, radius: float) -> DataFrame:
    """Contacts of equal spheres with real positions x, y, z: centres within twice the radius."""
    reach = 2 * radius * (1 + 1e-9)
    half = [(x, y, z) for x in (-1, 0, 1) for y in (-1, 0, 1) for z in (-1, 0, 1) if (x, y, z) >= (0, 0, 0)]
    steps = F.array(*[F.struct(*[F.lit(v).cast("long").alias(n) for v, n in zip(s, "xyz", strict=True)]) for s in half])
    cells = points.select("pid", "x", "y", "z", *[F.floor(F.col(n) / reach).cast("long").alias(f"b{n}") for n in "xyz"])
    a = cells.withColumn("s", F.explode(steps)).select(F.col("pid").alias("p"), *[F.col(n).alias(f"{n}_a") for n in "xyz"], ((F.col("s.x") == 0) & (F.col("s.y") == 0) & (F.col("s.z") == 0)).alias("own"), *[(F.col(f"b{n}") + F.col(f"s.{n}")).alias(f"b{n}") for n in "xyz"])
    b = cells.select(F.col("pid").alias("q"), *[F.col(n).alias(f"{n}_b") for n in "xyz"], "bx", "by", "bz")
    apart = sum((F.pow(F.col(f"{n}_a") - F.col(f"{n}_b"), 2) for n in "xyz"), F.lit(0.0))
    found = a.join(b.hint("merge"), ["bx", "by", "bz"]).filter((~F.col("own")) | (F.col("p") < F.col("q"))).filter(apart <= reach * reach)
    return found.select(F.least("p", "q").alias("pid_a"), F.greatest("p", "q").alias("pid_b"))


def ghosts(located: DataFrame, leaves: DataFrame, dom: Domain, halo: int) -> DataFrame:
    """Particles within `halo` of a foreign leaf: pid, owner cell, guest cell.

    A particle probes the cells of its own level around its leaf; a neighbour that is larger or smaller
    is met on the level at which it is a leaf.
    """
    deep = dom.max_level
    out = None
    probes = neighbours(located.select("pid", *AXES, *CELL), dom).withColumn("l", F.explode(F.expr(f"sequence(0, {deep})")))
    up = probes.filter("l <= level").select("pid", *AXES, *[F.col(c).alias(f"o_{c}") for c in CELL], F.col("l").cast("int").alias("level"), *[F.expr(f"shiftright(n{n}, level - l)").alias(f"c{n}") for n in "xyz"])
    out = up.join(leaves.select(*CELL), CELL)
    # smaller neighbours: they find the owner's cell as the ancestor of one of their own neighbours
    small = neighbours(leaves.select(*CELL), dom).withColumn("l", F.explode(F.expr("sequence(0, level)"))).filter("l < level")
    small = small.select(*[F.col(c).alias(f"g_{c}") for c in CELL], F.col("l").cast("int").alias("level"), *[F.expr(f"shiftright(n{n}, level - l)").alias(f"c{n}") for n in "xyz"]).distinct()
    down = located.select("pid", *AXES, *CELL).join(small, CELL)
    down = down.select("pid", *AXES, *[F.col(c).alias(f"o_{c}") for c in CELL], *[F.col(f"g_{c}").alias(c) for c in CELL])
    both = out.select(*down.columns).union(down).distinct()
    apart = F.lit(0).cast("long")
    for n, s in zip("xyz", dom.shifts, strict=True):
        lo, hi = F.expr(f"shiftleft(c{n}, cast({s} - level as int))"), F.expr(f"shiftleft(c{n} + 1, cast({s} - level as int)) - 1")
        gap = F.greatest(lo - F.col(f"g{n}"), F.col(f"g{n}") - hi, F.lit(0).cast("long"))
        apart = apart + gap * gap
    same = F.expr(" and ".join(f"{c} = o_{c}" for c in CELL))
    return both.filter(~same & (apart <= halo * halo)).select("pid", *[f"o_{c}" for c in CELL], *CELL)

"""Forest of octrees as tables: nodes are (level, cx, cy, cz), only leaves are stored."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cellbalance.operators.domain import Domain, cell_of, uniform_cells
from cellbalance.operators.store import written

CELL = ["level", "cx", "cy", "cz"]
STENCILS = {
    kind: [(x, y, z) for x in (-1, 0, 1) for y in (-1, 0, 1) for z in (-1, 0, 1) if 0 < abs(x) + abs(y) + abs(z) <= reach]
    for kind, reach in (("face", 1), ("edge", 2), ("corner", 3))
}


def leaf_id(prefix: str = "") -> Column:
    """A 62-bit id of a node that does not depend on the balancing curve and sorts like the cell."""
    level, x, y, z = (F.col(prefix + c).cast("long") for c in CELL)
    return F.shiftleft(level, 57) + F.shiftleft(x, 38) + F.shiftleft(y, 19) + z


def uniform(spark: SparkSession, dom: Domain, depth: int) -> DataFrame:
    """Leaves with every root refined `depth` times."""
    return uniform_cells(spark, dom, depth)


def split(nodes: DataFrame) -> DataFrame:
    """Eight children of each node, cut at its centre."""
    octants = F.array(*[F.struct(*[F.lit((o >> s) & 1).cast("long").alias(n) for n, s in (("x", 2), ("y", 1), ("z", 0))]) for o in range(8)])
    return nodes.select(*CELL, F.explode(octants).alias("o")).select(
        (F.col("level") + 1).alias("level"), *[(F.col(f"c{n}") * 2 + F.col(f"o.{n}")).alias(f"c{n}") for n in "xyz"]
    )


def parents(nodes: DataFrame) -> DataFrame:
    return nodes.select((F.col("level") - 1).alias("level"), *[F.shiftright(c, 1).alias(c) for c in CELL[1:]])


def merge(leaves: DataFrame, at_most: int = 0) -> DataFrame:
    """Parents whose eight children are all leaves with a summed weight of at most `at_most`."""
    up = leaves.filter("level > 0").select((F.col("level") - 1).alias("level"), *[F.shiftright(c, 1).alias(c) for c in CELL[1:]], "weight")
    return up.groupBy(*CELL).agg(F.count("*").alias("held"), F.sum("weight").alias("weight")).filter((F.col("held") == 8) & (F.col("weight") <= at_most)).drop("held")


def pyramid(points: DataFrame, dom: Domain, weight: Column | None = None) -> DataFrame:
    """Weights of the occupied cells of every level: rows collapse once, to finest cells."""
    finest = points.select(F.lit(dom.max_level).alias("level"), *cell_of(dom, dom.max_level), (F.lit(1) if weight is None else weight).cast("long").alias("w"))
    level = finest.groupBy(*CELL).agg(F.sum("w").alias("weight"))
    levels = [level]
    for _ in range(dom.max_level):
        level = level.groupBy((F.col("level") - 1).alias("level"), *[F.shiftright(c, 1).alias(c) for c in CELL[1:]]).agg(F.sum("weight").alias("weight"))
        levels.append(level)
    return reduce(DataFrame.union, levels)


def weighed(nodes: DataFrame, pyr: DataFrame) -> DataFrame:
    """Nodes with their weight; empty cells weigh 0. The occupied cells follow the table, and millions of them
    lie in few bytes of a file, which Spark takes for small enough to broadcast: they are merged."""
    return nodes.join(pyr.hint("merge"), CELL, "left").select(*CELL, F.coalesce("weight", F.lit(0)).cast("long").alias("weight"))


def total(pyr: DataFrame) -> DataFrame:
    return pyr.filter("level = 0").agg(F.coalesce(F.sum("weight"), F.lit(0)).alias("total"))


def over_mean(pyr: DataFrame, dom: Domain, p: int, factor: int = 1) -> DataFrame:
    """Nodes to refine: weight * p * factor > total, below the deepest level."""
    return pyr.join(F.broadcast(total(pyr))).filter(f"weight * {p * factor} > total and level < {dom.max_level}").select(*CELL, "weight")


def interior_of(leaves: DataFrame, dom: Domain) -> DataFrame:
    """All proper ancestors of the leaves."""
    found, level = [], leaves.select(*CELL).filter("level > 0")
    for _ in range(dom.max_level):
        level = parents(level).distinct()
        found.append(level)
        level = level.filter("level > 0")
    return reduce(DataFrame.union, found).distinct() if found else leaves.select(*CELL).limit(0)


def leaves_of(interior: DataFrame, spark: SparkSession, dom: Domain) -> DataFrame:
    """Roots and children of interior nodes that are not interior themselves."""
    return uniform_cells(spark, dom, 0).union(split(interior)).join(interior, CELL, "left_anti")


def adaptive(spark: SparkSession, pyr: DataFrame, dom: Domain, p: int, factor: int = 1) -> DataFrame:
    """Leaves of the tree in which every node over the threshold is refined, to full depth."""
    return weighed(leaves_of(over_mean(pyr, dom, p, factor).select(*CELL), spark, dom), pyr)


def adapt(
    leaves: DataFrame, pyr: DataFrame, dom: Domain, p: int, mode: str = "both", factor: int = 1, coarsen_at_most: int = 0, max_delta: int = 1, keep_empty: bool = True
) -> DataFrame:
    """`max_delta` passes, in each of which leaves over the threshold split once and eight light siblings
    merge, so a leaf changes by as many levels at most. Without `keep_empty` the forest is sparse: leaves
    of weight 0 are left out at the end."""
    for k in range(max_delta):
        leaves = _pass(leaves if k == 0 else written(leaves), pyr, dom, p, mode, factor, coarsen_at_most)
    return leaves if keep_empty else leaves.filter("weight > 0")


def _pass(leaves: DataFrame, pyr: DataFrame, dom: Domain, p: int, mode: str, factor: int, coarsen_at_most: int) -> DataFrame:
    if mode not in ("both", "refine", "coarsen"):
        raise ValueError(f"unknown mode {mode}")
    hot = over_mean(pyr, dom, p, factor).select(*CELL) if mode != "coarsen" else leaves.select(*CELL).limit(0)
    merged = merge(leaves, coarsen_at_most).select(*CELL) if mode != "refine" else leaves.select(*CELL).limit(0)
    hot = leaves.select(*CELL).join(hot, CELL, "left_semi")
    gone = hot.union(split(merged))
    return weighed(leaves.select(*CELL).join(gone, CELL, "left_anti").union(split(hot)).union(merged), pyr)


def neighbours(nodes: DataFrame, dom: Domain, kind: str = "corner") -> DataFrame:
    """In-box cells of the same level around each node, as (nx, ny, nz); walls do not wrap."""
    steps = F.array(*[F.struct(*[F.lit(v).cast("long").alias(n) for v, n in zip(s, "xyz", strict=True)]) for s in STENCILS[kind]])
    around = nodes.withColumn("s", F.explode(steps))
    for n, r in zip("xyz", dom.roots, strict=True):
        around = around.withColumn(f"n{n}", F.col(f"c{n}") + F.col(f"s.{n}")).filter((F.col(f"n{n}") >= 0) & (F.col(f"n{n}") < F.expr(f"shiftleft(cast({r} as bigint), level)")))
    return around.drop("s")


def close_two_to_one(interior: DataFrame, dom: Domain, kind: str = "corner") -> DataFrame:
    """The smallest interior set whose leaves differ by one level at most across neighbours: one sweep
    from fine to coarse, each level forcing the parents of its nodes and of their neighbours."""
    closed, level = [], interior.filter(F.col("level") == dom.max_level - 1)
    for k in range(dom.max_level - 1, -1, -1):
        closed.append(level)
        if k:
            around = neighbours(level, dom, kind).select("level", *[F.col(f"n{n}").alias(f"c{n}") for n in "xyz"])
            level = parents(level.select(*CELL).union(around)).union(interior.filter(F.col("level") == k - 1).select(*CELL)).distinct()
    return reduce(DataFrame.union, [c.select(*CELL) for c in closed])


def closed_leaves(spark: SparkSession, leaves: DataFrame, pyr: DataFrame, dom: Domain, kind: str = "corner", keep_empty: bool = True) -> DataFrame:
    """The leaves closed under the two-to-one rule; without `keep_empty` those of weight 0 are left out."""
    out = weighed(leaves_of(close_two_to_one(interior_of(leaves, dom), dom, kind), spark, dom), pyr)
    return out if keep_empty else out.filter("weight > 0")


def locate(points: DataFrame, leaves: DataFrame, dom: Domain) -> DataFrame:
    """points with the leaf that holds each: one equality join per row, on the leaf of its finest cell.

    Leaves are spread to the finest cells they cover only where points are, so the join is on cells.
    """
    cells = points.withColumns({f"_{c}": e for c, e in zip(CELL[1:], cell_of(dom, dom.max_level), strict=True)})
    seen = cells.select(*[F.col(f"_{c}").alias(f"f{c}") for c in CELL[1:]]).distinct()
    up = seen.withColumn("level", F.explode(F.sequence(F.lit(0), F.lit(dom.max_level))))
    up = up.select("*", *[F.expr(f"shiftright(f{c}, {dom.max_level} - level)").alias(c) for c in CELL[1:]])
    of = up.join(leaves.select(*CELL), CELL)
    return cells.join(of, [F.col(f"_{c}") == F.col(f"f{c}") for c in CELL[1:]]).drop(*[f"_{c}" for c in CELL[1:]], *[f"f{c}" for c in CELL[1:]])

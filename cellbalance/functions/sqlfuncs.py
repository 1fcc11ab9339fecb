"""Functions for SQL users: keys and cells as temporary SQL functions, tree steps as table functions."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from cellbalance.operators.octree import STENCILS


@udtf(returnType="level int, cx long, cy long, cz long")
class OctreeChildren:
    def eval(self, level: int, cx: int, cy: int, cz: int):
        for o in range(8):
            yield level + 1, 2 * cx + (o >> 2), 2 * cy + (o >> 1 & 1), 2 * cz + (o & 1)


@udtf(returnType="level int, cx long, cy long, cz long")
class Stencil:
    def eval(self, level: int, cx: int, cy: int, cz: int, kind: str):
        for x, y, z in STENCILS[kind]:
            yield level, cx + x, cy + y, cz + z


def register(spark: SparkSession) -> None:
    """cell_of(g, shift), morton_key(x, y, z) for ten bits an axis, octree_children(...), stencil(...)."""
    spark.udtf.register("octree_children", OctreeChildren)
    spark.udtf.register("stencil", Stencil)
    spark.sql("create or replace temporary function cell_of(g bigint, shift int) returns bigint return shiftright(g, shift)")
    bits = " + ".join(f"shiftleft(shiftright({a}, {b}) & 1, {3 * b + s})" for b in range(10) for a, s in (("x", 2), ("y", 1), ("z", 0)))
    spark.sql(f"create or replace temporary function morton_key(x bigint, y bigint, z bigint) returns bigint return {bits}")

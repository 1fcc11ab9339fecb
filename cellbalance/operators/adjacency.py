"""Which leaves touch: probe joins on cells, never all pairs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellbalance.operators.domain import Domain
from cellbalance.operators.octree import CELL, neighbours

PAIR = ["src_level", "src_x", "src_y", "src_z", "dst_level", "dst_x", "dst_y", "dst_z"]


def full(leaves: DataFrame, dom: Domain, kind: str = "corner") -> DataFrame:
    """Ordered pairs of touching leaves, each once with the smaller cell first in (level, x, y, z).

    A leaf probes its same-size neighbours and their ancestors, so it finds equal and larger leaves;
    larger ones find it in turn through the same row.
    """
    probes = neighbours(leaves.select(*CELL), dom, kind).withColumn("l", F.explode(F.expr("sequence(0, level)")))
    probes = probes.select(
        *[F.col(c).alias(f"a_{c}") for c in CELL], F.col("l").cast("int").alias("level"), *[F.expr(f"shiftright(n{n}, level - l)").alias(f"c{n}") for n in "xyz"]
    )
    found = probes.join(leaves.select(*CELL), CELL)
    a, b = F.struct(*[F.col(f"a_{c}").cast("long").alias(c) for c in CELL]), F.struct(*[F.col(c).cast("long").alias(c) for c in CELL])
    both = found.select(F.least(a, b).alias("s"), F.greatest(a, b).alias("d")).filter("s <> d").distinct()
    return both.select(*[F.col(f"{e}.{c}").alias(f"{n}_{c.replace('c', '') if c != 'level' else c}") for e, n in (("s", "src"), ("d", "dst")) for c in CELL])


def faces(leaves: DataFrame, dom: Domain) -> DataFrame:
    """Pairs that share a face, with its area in units of the finest cells."""
    pairs, deep = full(leaves, dom, "face"), dom.max_level
    area, flat = F.lit(1).cast("long"), F.lit(0)
    for n in "xyz":
        lo = F.greatest(*[F.expr(f"shiftleft({e}_{n}, cast({deep} - {e}_level as int))") for e in ("src", "dst")])
        hi = F.least(*[F.expr(f"shiftleft({e}_{n} + 1, cast({deep} - {e}_level as int))") for e in ("src", "dst")])
        area = area * F.greatest(hi - lo, F.lit(1).cast("long"))
        flat = flat + (hi == lo).cast("int")
    return pairs.withColumn("area", area).withColumn("flat", flat).filter("flat = 1").drop("flat")


def violations(leaves: DataFrame, dom: Domain) -> DataFrame:
    """Touching leaves that differ by two levels or more."""
    return full(leaves, dom).filter(F.abs(F.col("src_level") - F.col("dst_level")) >= 2)

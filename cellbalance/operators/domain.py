"""Box, lattice and root bricks: rows with coordinates to integer cells."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

LATTICE = 1024


@dataclass(frozen=True)
class Domain:
    """A box in lattice units, cut into equal root bricks; cells of level l halve a root l times."""

    roots: tuple[int, int, int]
    max_level: int
    side: tuple[int, int, int] = (LATTICE, LATTICE, LATTICE)
    lo: tuple[int, int, int] | None = None
    hi: tuple[int, int, int] | None = None

    def __post_init__(self):
        # leaf ids hold 19 bits a coordinate, keys 3 * 20 bits
        if max(self.roots) << self.max_level > 1 << 19:
            raise ValueError("the finest grid has more than 2^19 cells along an axis: cut the box into several domains")

    @property
    def shifts(self) -> tuple[int, ...]:
        """Bits of a root brick along each axis."""
        return tuple((s // r).bit_length() - 1 for s, r in zip(self.side, self.roots, strict=True))

    @property
    def key_bits(self) -> int:
        """Bits an axis of the padded finest grid needs."""
        return max((max(self.roots) << self.max_level) - 1, 1).bit_length()

    def cells(self, level: int) -> tuple[int, ...]:
        return tuple(r << level for r in self.roots)


def fixed(roots: tuple[int, int, int], max_level: int, **kwargs) -> Domain:
    return Domain(roots, max_level, **kwargs)


def fit(df: DataFrame, cols: tuple[str, str, str], roots: tuple[int, int, int], max_level: int) -> Domain:
    """The box of the data: one scan, six numbers to the driver."""
    row = df.agg(*[f(c).cast("long") for c in cols for f in (F.min, F.max)]).first()
    if row[0] is None:
        return Domain(roots, max_level, lo=(0, 0, 0), hi=(0, 0, 0))
    return Domain(roots, max_level, lo=tuple(row[0::2]), hi=tuple(row[1::2]))


def bounds(df: DataFrame, cols: tuple[str, str, str]) -> DataFrame:
    """The box as a one-row table, for plans without a driver round trip."""
    return df.agg(*[f(c).cast("long").alias(f"{n}_{end}") for c, n in zip(cols, "xyz", strict=True) for f, end in ((F.min, "lo"), (F.max, "hi"))])


def quantize(df: DataFrame, cols: tuple[str, str, str], dom: Domain | None = None) -> DataFrame:
    """df with gx, gy, gz in [0, lattice): exact integer division over the box of the whole table.

    Without a domain's box the bounds come from df itself as a one-row broadcast. Rows with a null
    coordinate are rejected: they have no place in the box.
    """
    df = df.dropna(subset=list(cols))
    if dom is not None and dom.lo is not None:
        edges = [(F.lit(lo), F.lit(hi)) for lo, hi in zip(dom.lo, dom.hi, strict=True)]
    else:
        df = df.join(F.broadcast(bounds(df, cols)))
        edges = [(F.col(f"{n}_lo"), F.col(f"{n}_hi")) for n in "xyz"]
    side = dom.side if dom is not None else (LATTICE,) * 3
    parts = [F.expr(f"({c} - _lo{i}) * {side[i]} div (_hi{i} - _lo{i} + 1)").alias(f"g{n}") for i, (c, n) in enumerate(zip(cols, "xyz", strict=True))]
    keep = [c for c in df.columns if c not in {f"{n}_{e}" for n in "xyz" for e in ("lo", "hi")}]
    df = df.select(*keep, *[e.cast("long").alias(f"_{k}{i}") for i, pair in enumerate(edges) for e, k in zip(pair, ("lo", "hi"), strict=True)])
    return df.select(*keep, *parts)


def cell_of(dom: Domain, level: int, names: tuple[str, str, str] = ("gx", "gy", "gz")) -> list[Column]:
    return [F.shiftright(F.col(g), s - level).cast("long").alias(c) for g, s, c in zip(names, dom.shifts, ("cx", "cy", "cz"), strict=True)]


def roots(spark: SparkSession, dom: Domain) -> DataFrame:
    return uniform_cells(spark, dom, 0)


def uniform_cells(spark: SparkSession, dom: Domain, level: int) -> DataFrame:
    nx, ny, nz = dom.cells(level)
    i = F.col("id")
    return spark.range(nx * ny * nz).select(
        F.lit(level).alias("level"), F.expr(f"id div {ny * nz}").alias("cx"), (F.expr(f"id div {nz}") % ny).alias("cy"), (i % nz).alias("cz")
    )

"""Particles on lattices: generators from ranges, and a partitioned Python data source."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "pid long, x double, y double, z double, radius double"


def cubic(spark: SparkSession, nx: int, ny: int, nz: int, spacing: float = 1.0) -> DataFrame:
    return cubic_of(spark.range(nx * ny * nz), ny, nz, spacing)


def cubic_of(ids: DataFrame, ny: int, nz: int, spacing: float = 1.0) -> DataFrame:
    """Simple cubic lattice of a particle for each id, filled along z, y and x; neighbours touch when the radius is half the spacing. Velocities within
    +-1 come from a hash of the particle, so every run has the same ones."""
    i = ids.select(F.col("id").alias("pid"), F.expr(f"id div {ny * nz}").alias("i"), F.expr(f"id div {nz} % {ny}").alias("j"), (F.col("id") % nz).alias("k"))
    speed = [(F.pmod(F.xxhash64("pid", F.lit(s)), F.lit(2001)) / 1000 - 1).alias(f"v{n}") for s, n in enumerate("xyz")]
    return i.select("pid", *[(F.col(c) * spacing).cast("double").alias(n) for c, n in zip("ijk", "xyz", strict=True)], *speed, F.lit(spacing / 2).alias("radius"))


def hcp(spark: SparkSession, nx: int, ny: int, nz: int, radius: float = 0.5) -> DataFrame:
    return hcp_of(spark.range(nx * ny * nz), ny, nz, radius)


def hcp_of(ids: DataFrame, ny: int, nz: int, radius: float = 0.5) -> DataFrame:
    """Hexagonal close packing of a particle for each id: layers of triangles, every other layer shifted into the gaps; twelve
    neighbours inside."""
    i = ids.select(F.col("id").alias("pid"), F.expr(f"id div {ny * nz}").alias("i"), F.expr(f"id div {nz} % {ny}").alias("j"), (F.col("id") % nz).alias("k"))
    odd = F.col("k") % 2
    x = (2 * F.col("i") + (F.col("j") + F.col("k")) % 2) * radius
    y = F.sqrt(F.lit(3.0)) * (F.col("j") + odd / 3.0) * radius
    z = 2 * F.sqrt(F.lit(6.0)) / 3 * F.col("k") * radius
    return i.select("pid", x.cast("double").alias("x"), y.alias("y"), z.alias("z"), F.lit(radius).alias("radius"))


def drop(points: DataFrame, step: int, dt: float = 0.01) -> DataFrame:
    """Closed-form free fall after `step` steps under unit gravity in -z; contacts are not resolved."""
    t = step * dt
    return points.withColumn("z", F.greatest(F.col("radius"), F.col("z") + F.col("vz") * t - F.lit(0.5 * t * t)))


class LatticePartition(InputPartition):
    def __init__(self, low: int, high: int):
        self.low, self.high = low, high


class LatticeReader(DataSourceReader):
    def __init__(self, options: dict):
        self.n = [int(options.get(k, 10)) for k in ("nx", "ny", "nz")]
        self.spacing, self.parts = float(options.get("spacing", 1.0)), int(options.get("partitions", 4))

    def partitions(self) -> list[LatticePartition]:
        total = self.n[0] * self.n[1] * self.n[2]
        return [LatticePartition(total * k // self.parts, total * (k + 1) // self.parts) for k in range(self.parts)]

    def read(self, part: LatticePartition):
        _, ny, nz = self.n
        for i in range(part.low, part.high):
            yield i, i // (ny * nz) * self.spacing, i // nz % ny * self.spacing, i % nz * self.spacing, self.spacing / 2


class LatticeSource(DataSource):
    """spark.dataSource.register(LatticeSource); spark.read.format("lattice").option("nx", 20).load()"""

    @classmethod
    def name(cls) -> str:
        return "lattice"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> LatticeReader:
        return LatticeReader(self.options)

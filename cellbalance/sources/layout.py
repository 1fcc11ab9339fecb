"""Physical layout: rows written by rank and curve key, read back by key ranges."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellbalance.operators import octree, sfc
from cellbalance.operators.domain import Domain
from cellbalance.operators.octree import CELL


def write(points: DataFrame, asg: DataFrame, dom: Domain, p: int, path: str, curve: str = "hilbert", most_buckets: int = 4096) -> None:
    """Rows to Parquet, partitioned by rank bucket and sorted by curve key inside files, so that row
    group statistics skip. Ranks beyond the bucket budget share buckets of neighbouring ranks."""
    per = -(-p // min(p, most_buckets))
    placed = octree.locate(points, asg, dom).join(asg.select(*CELL, "rank_id"), CELL)
    keyed = sfc.keyed(placed, dom, curve).withColumn("bucket", F.expr(f"rank_id div {per}"))
    keyed.repartition("bucket").sortWithinPartitions("bucket", "curve_key").write.mode("overwrite").partitionBy("bucket").parquet(path)


def read_box(spark: SparkSession, path: str, dom: Domain, low: tuple[int, int, int], high: tuple[int, int, int], level: int, curve: str = "hilbert") -> DataFrame:
    """Rows whose leaf may lie in a box of cells: a disjunction of key ranges that Parquet can skip by."""
    df, test = spark.read.parquet(path), F.lit(False)
    for a, b in sfc.ranges_for_box(dom, low, high, level, curve):
        test = test | ((F.col("curve_key") >= a) & (F.col("curve_key") < b))
    return df.filter(test)


def moved_rows(points: DataFrame, migration: DataFrame, dom: Domain) -> DataFrame:
    """Only the rows of leaves that changed rank: what an incremental rewrite touches."""
    return octree.locate(points, migration, dom)


def bucketed(points: DataFrame, asg: DataFrame, dom: Domain, table: str, buckets: int = 8) -> None:
    """Rows with their rank as a table bucketed by rank, so that later joins on it need no shuffle."""
    placed = octree.locate(points, asg, dom).join(asg.select(*CELL, "rank_id"), CELL)
    placed.write.mode("overwrite").bucketBy(buckets, "rank_id").sortBy("rank_id").saveAsTable(table)

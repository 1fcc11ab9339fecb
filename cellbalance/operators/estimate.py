"""A-priori gains of a filled box: compute and communication, ideal and limited by leaf size."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def ideal_compute(largest: Column, mean: Column) -> Column:
    return largest / mean


def granular_compute(largest: Column, mean: Column, leaf: Column) -> Column:
    """The most loaded rank ends about one leaf above the mean."""
    return largest / (mean + leaf)


def communication(fill: Column, depth: Column) -> Column:
    """More ranks share the work (1 / fill), but each refinement doubles the surface."""
    return (1 / fill) / F.pow(F.lit(2.0), depth)


def table(workloads: DataFrame) -> DataFrame:
    """workload, fill, depth, largest, mean, leaf to the three gains."""
    c = F.col
    return workloads.select(
        "workload",
        F.round(ideal_compute(c("largest"), c("mean")), 6).alias("ideal"),
        F.round(granular_compute(c("largest"), c("mean"), c("leaf")), 6).alias("granular"),
        F.round(communication(c("fill"), c("depth")), 6).alias("communication"),
    )

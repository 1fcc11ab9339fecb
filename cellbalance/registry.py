"""Queries of the engine and their SQL, by name."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from cellbalance.catalog import ORACLES, QUERIES
from cellbalance.plans import extras, graph, hopper, measures, relational, scaling, surface, timing, wedge  # noqa: F401  they register queries
from cellbalance.streaming import rebalance  # noqa: F401

__all__ = ["ORACLES", "QUERIES", "flagship"]


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return QUERIES["hilbert_midpoint_assign"](spark, sf_dir)

"""Registered queries and their SQL twins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from nudgegraph.workloads import experiments, heuristics, networks, sampled, streamq, toolkit, treeq

_PARTS = [networks, sampled, heuristics, treeq, streamq, toolkit, experiments]

QUERIES: dict = {}
ORACLES: dict = {}
for _part in _PARTS:
    QUERIES |= _part.QUERIES
    ORACLES |= _part.ORACLES


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return QUERIES["select_lower_bound_r"](spark, sf_dir)

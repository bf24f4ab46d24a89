"""Readers and writers of edge lists and run logs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nudgegraph.model import EDGES, assert_schema

RUNS = "exp string, net string, solver string, seeds_mode string, k int, beta double, eps double, rep int, measure string, value double, stderr double"


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """Edges from parquet, orc, csv or json; text formats take the fixed schema, not a guess."""
    if fmt in ("parquet", "orc"):
        return assert_schema(spark.read.format(fmt).load(path), EDGES)
    reader = spark.read.schema(EDGES).format(fmt)
    return (reader.option("header", True) if fmt == "csv" else reader).load(path)


def write_edges(edges: DataFrame, path: str, fmt: str = "parquet") -> None:
    """Edges as files; text formats, many times larger than the others, are compressed."""
    writer = assert_schema(edges, EDGES).write.mode("overwrite").format(fmt)
    if fmt not in ("parquet", "orc"):
        writer = writer.option("compression", "gzip")
    (writer.option("header", True) if fmt == "csv" else writer).save(path)


def save_clustered(edges: DataFrame, table: str, by: str = "dst", buckets: int = 64) -> None:
    """A bucketed and sorted table: searches from ``by`` join it without moving it."""
    edges.write.mode("overwrite").bucketBy(buckets, by).sortBy(by).saveAsTable(table)


def append_runs(runs: DataFrame, path: str) -> None:
    """Write a run log; a repeated write of an experiment replaces its own part only."""
    runs.write.mode("overwrite").partitionBy("exp", "net").option("partitionOverwriteMode", "dynamic").parquet(path)


def literal_graph(spark: SparkSession, rows: list[tuple[int, int, float, float]]) -> DataFrame:
    return spark.createDataFrame(rows, EDGES)


def edge_quantiles(edges: DataFrame, shares: tuple[float, ...] = (0.25, 0.5, 0.75)) -> DataFrame:
    return edges.agg(F.percentile_approx("p", list(shares)).alias("p"))

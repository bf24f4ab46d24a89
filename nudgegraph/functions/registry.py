"""SQL functions, table functions and a data source for SQL users."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from nudgegraph.functions.coins import coin_array, root_array
from nudgegraph.operators.kernels import activates, marginal_nodes

SQL_FUNCTIONS = {
    "boosted_prob": "(p DOUBLE, beta DOUBLE) RETURNS DOUBLE RETURN 1 - power(1 - p, beta)",
    "coin_number": "(salt BIGINT, world BIGINT, src BIGINT, dst BIGINT) RETURNS BIGINT RETURN CAST(conv(substr(md5(concat_ws('|', salt, world, src, dst)), 1, 8), 16, 10) AS BIGINT)",
    "coin_state": "(salt BIGINT, world BIGINT, src BIGINT, dst BIGINT, p DOUBLE, q DOUBLE) RETURNS STRING RETURN CASE"
    " WHEN CAST(conv(substr(md5(concat_ws('|', salt, world, src, dst)), 1, 8), 16, 10) AS BIGINT) < floor(p * 4294967296) THEN 'live'"
    " WHEN CAST(conv(substr(md5(concat_ws('|', salt, world, src, dst)), 1, 8), 16, 10) AS BIGINT) < floor(q * 4294967296) THEN 'raised' ELSE 'blocked' END",
    "floor_to": "(x DOUBLE, step DOUBLE) RETURNS DOUBLE RETURN CASE WHEN step = 0 THEN x ELSE floor(x / step + 1e-9) * step END",
}


@F.udtf(returnType="sketch bigint, root bigint")
class SketchRoots:
    """Roots of a range of sketches over n nodes numbered from 0."""

    def eval(self, first: int, last: int, salt: int, n: int) -> Iterator[tuple[int, int]]:
        import numpy as np

        ids = np.arange(first, last)
        yield from zip(ids.tolist(), (root_array("portable", salt, ids) % n).tolist(), strict=True)


@F.udtf(returnType="world bigint, src bigint, dst bigint, coin bigint")
class WorldCoins:
    """Coins of one edge over a range of worlds."""

    def eval(self, src: int, dst: int, worlds: int, salt: int) -> Iterator[tuple[int, int, int, int]]:
        import numpy as np

        ids = np.arange(worlds)
        for w, h in zip(ids.tolist(), coin_array("portable", salt, ids, src, dst).tolist(), strict=True):
            yield w, src, dst, h


@F.udtf(returnType="node bigint, depth int")
class TreeLevels:
    """Depths of one tree's nodes from its (node, parent) rows; use it with PARTITION BY the tree."""

    def __init__(self):
        self.children: dict[int, list[int]] = {}

    def eval(self, row) -> None:
        self.children.setdefault(row["parent"], []).append(row["node"])

    def terminate(self) -> Iterator[tuple[int, int]]:
        nodes = {v for kids in self.children.values() for v in kids}
        now, depth = sorted(set(self.children) - nodes), 0
        while now:
            for v in now:
                yield v, depth
            now, depth = [w for v in now for w in self.children.get(v, ())], depth + 1


class TreeSource(DataSource):
    """``spark.read.format("binary_tree").option("nodes", n)``: (node, parent) in level order."""

    @classmethod
    def name(cls) -> str:
        return "binary_tree"

    def schema(self) -> str:
        return "node bigint, parent bigint"

    def reader(self, schema) -> DataSourceReader:
        return _TreeReader(int(self.options.get("nodes", "1")), int(self.options.get("parts", "4")))


class _TreeReader(DataSourceReader):
    def __init__(self, n: int, parts: int):
        self.n, self.parts = n, max(1, parts)

    def partitions(self) -> list[InputPartition]:
        step = -(-max(0, self.n - 1) // self.parts) or 1
        return [InputPartition((lo, min(self.n, lo + step))) for lo in range(1, max(self.n, 2), step)]

    def read(self, partition: InputPartition) -> Iterator[tuple[int, int]]:
        lo, hi = partition.value
        for i in range(lo, hi):
            yield i, (i - 1) // 2


def sketch_activates(boost: list[int]):
    """Column function (root, edges) -> boolean for a set to boost."""
    chosen = set(boost)

    @F.pandas_udf("boolean")
    def run(root: pd.Series, edges: pd.Series) -> pd.Series:
        return pd.Series([activates(r, [(e["src"], e["dst"], e["live"]) for e in es], chosen) for r, es in zip(root, edges, strict=True)])

    return run


def sketch_marginal_nodes(boost: list[int]):
    """Column function (root, edges) -> nodes that newly activate the root."""
    chosen = set(boost)

    @F.pandas_udf("array<bigint>")
    def run(root: pd.Series, edges: pd.Series) -> pd.Series:
        return pd.Series([marginal_nodes(r, [(e["src"], e["dst"], e["live"]) for e in es], chosen) for r, es in zip(root, edges, strict=True)])

    return run


def register(spark: SparkSession) -> None:
    """Make all functions and the source known to the session's SQL."""
    for name, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    spark.udtf.register("sketch_roots", SketchRoots)
    spark.udtf.register("world_coins", WorldCoins)
    spark.udtf.register("tree_levels", TreeLevels)
    spark.dataSource.register(TreeSource)

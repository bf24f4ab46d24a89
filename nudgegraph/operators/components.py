"""Connected components by alternating star contractions.

What tasks find connected among their own edges they contract first. Each round
is two joins and two partially aggregated minima, so a hub costs its edges
once; the number of rounds is logarithmic in practice. A graph of a few
thousand edges is contracted by one task instead. Nothing is collected but two
counters a round.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nudgegraph.session import Scratch


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
    return both.join(least, "a").where(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = down.groupBy("a").agg(F.min("b").alias("m"))
    moved = down.join(least, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return moved.unionByName(least.select("a", F.col("m").alias("b"))).where("a <> b").distinct()


#: edges that one task may contract, and edges after which a task passes on what it has
ONE_TASK, AT_ONCE = 16_384, 500_000


def _contracted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Edges from each node to the least of those that this task's edges connect it with."""
    up: dict[int, int] = {}
    seen = 0

    def root(x: int) -> int:
        up.setdefault(x, x)
        while up[x] != x:
            up[x] = x = up[up[x]]
        return x

    def out() -> pa.RecordBatch:
        pairs = [(x, r) for x in up if (r := root(x)) != x]
        a, b = zip(*pairs, strict=True) if pairs else ((), ())
        up.clear()
        return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    for batch in batches:
        for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            a, b = root(a), root(b)
            up[max(a, b)] = min(a, b)
        seen += batch.num_rows
        if seen >= AT_ONCE:
            yield out()
            seen = 0
    yield out()


def components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """(node, component) for every node that has an edge to another node.

    ``edges`` holds two id columns; direction, repeats, loops and nulls do not
    matter. A component's id is its smallest node. Nodes without an edge are
    not returned; an empty input gives an empty result.
    """
    spark = edges.sparkSession
    scratch = Scratch(spark, "components")
    now = edges.select(F.col(a).alias("a"), F.col(b).alias("b")).where("a is not null and b is not null and a <> b")
    now = now.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b")).mapInArrow(_contracted, "a long, b long")
    now = scratch.keep(now.distinct(), "edges")
    print_of = lambda df: tuple(df.agg(F.count("*"), F.bit_xor(F.xxhash64("a", "b"))).first())
    seen = print_of(now)
    if seen[0] <= ONE_TASK:
        now = scratch.keep(now.coalesce(1).mapInArrow(_contracted, "a long, b long"), "edges")
        max_rounds = 0
    for left in range(max_rounds, 0, -1):
        after = scratch.keep(_small_star(_large_star(now)), "edges")
        scratch.drop(now)
        now, last = after, seen
        seen = print_of(now)
        if seen == last:
            break
        if left == 1:
            raise RuntimeError("components did not settle")
    roots = now.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct()
    return now.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(roots)

"""Schemas and the objects that solvers work on."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from nudgegraph.session import Scratch

EDGES = T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType()), T.StructField("p", T.DoubleType()), T.StructField("q", T.DoubleType())])
SKETCHES = (
    "sketch long, root long, category string, edges array<struct<src:long,dst:long,live:boolean>>, critical array<long>,"
    " n_raw_edges long, n_edges int, n_touched long"
)
#: stands for all nodes that seeds reach by live edges
SUPER = -1


def assert_schema(df: DataFrame, schema: T.StructType) -> DataFrame:
    """``df`` with just the schema's columns; raises on a missing or mistyped one."""
    have = {f.name: f.dataType for f in df.schema.fields}
    wrong = [f"{f.name}: {have.get(f.name)}" for f in schema.fields if have.get(f.name) != f.dataType]
    if wrong:
        raise TypeError(f"unfit columns: {wrong}")
    return df.select(*schema.fieldNames())


def with_boost(edges: DataFrame, beta: float = 2.0) -> DataFrame:
    """Raised probability q = 1 - (1-p)^beta; multiplied out for whole beta."""
    miss = 1 - F.col("p")
    if float(beta).is_integer() and 1 <= beta <= 16:
        left = miss
        for _ in range(int(beta) - 1):
            left = left * miss
    else:
        left = F.pow(miss, F.lit(float(beta)))
    return edges.withColumn("q", 1 - left)


def dense_nodes(edges: DataFrame) -> DataFrame:
    """(node, idx) with idx 0..n-1 in the order of nodes.

    A range partitioning and one small count a partition give the offsets; no
    partition ever holds all nodes. The ranges come from a sample that differs
    from run to run, so the partitioned rows are written before they are counted.
    """
    nodes = edges.select(F.col("src").alias("node")).unionByName(edges.select(F.col("dst").alias("node"))).distinct()
    ranged = nodes.repartitionByRange("node").sortWithinPartitions("node").withColumn("part", F.spark_partition_id()).withColumn("row", F.monotonically_increasing_id())
    ranged = Scratch(edges.sparkSession, "graph").keep(ranged.withColumn("row", F.expr("row & ((1L << 33) - 1)")), "ranges")
    counts = ranged.groupBy("part").count().collect()
    offset, total = {}, 0
    for r in sorted(counts, key=lambda r: r.part):
        offset[r.part], total = total, total + r["count"]
    if not offset:
        return nodes.select("node", F.lit(0).cast("long").alias("idx"))
    table = F.create_map(*[F.lit(x).cast(t) for k, v in offset.items() for x, t in ((k, "int"), (v, "long"))])
    return ranged.select("node", (F.col("row") + F.element_at(table, F.col("part"))).alias("idx"))


@dataclass(frozen=True)
class BoostGraph:
    """A directed graph whose edges have a base and a raised probability."""

    edges: DataFrame

    @classmethod
    def from_edges(cls, edges: DataFrame, beta: float = 2.0) -> BoostGraph:
        return cls(assert_schema(edges if "q" in edges.columns else with_boost(edges, beta), EDGES))

    @classmethod
    def from_actions(cls, actions: DataFrame, ties: DataFrame | None, window: str, beta: float = 2.0, scale: float = 1.0) -> BoostGraph:
        from nudgegraph.sources.networks import learn_probabilities

        return cls.from_edges(learn_probabilities(actions, ties, window, scale), beta)

    def raised(self, beta: float) -> BoostGraph:
        """The same edges raised with another exponent, as a written table; worlds in which nothing is boosted stay as they are."""
        other = BoostGraph(Scratch(self.spark, "net").keep(BoostGraph.from_edges(self.edges.select("src", "dst", "p"), beta).edges, "raised"))
        other.__dict__["_worlds"] = self.__dict__.setdefault("_worlds", {})
        return other

    @property
    def spark(self) -> SparkSession:
        return self.edges.sparkSession

    @cached_property
    def nodes(self) -> DataFrame:
        """(node, idx), from a written table: every search and baseline starts from it."""
        return dense_nodes(self.edges)

    @cached_property
    def n(self) -> int:
        return self.nodes.count()

    @cached_property
    def m(self) -> int:
        return self.edges.count()


@dataclass(frozen=True)
class BoostProblem:
    """Choose at most k nodes to boost, given the seeds."""

    graph: BoostGraph
    seeds: DataFrame
    k: int

    @cached_property
    def seed_ids(self) -> list[int]:
        """Seeds are input of a bounded size: the solvers send them to all workers."""
        rows = self.seeds.select("node").distinct().limit(1_000_001).collect()
        if len(rows) > 1_000_000:
            raise ValueError("more than a million seeds")
        return sorted(r.node for r in rows)

    def candidates(self) -> DataFrame:
        return self.graph.nodes.join(self.seeds.select("node").distinct(), "node", "left_anti")


@dataclass
class RunReport:
    """What a solver did: counts, ratios, guarantees, seconds by phase."""

    values: dict = field(default_factory=dict)

    def __getattr__(self, name: str):
        try:
            return self.__dict__["values"][name]
        except KeyError:
            raise AttributeError(name) from None


@dataclass
class Solution:
    boost: list[int]
    report: RunReport
    sketches: DataFrame | None = None

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(i, b) for i, b in enumerate(self.boost)], "rank int, node long")

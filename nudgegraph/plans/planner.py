"""Physical choices: which form of an operator runs, by checked sizes."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nudgegraph.functions.coins import SPAN
from nudgegraph.model import BoostGraph

#: edges that may be sent to every worker; above it searches run as joins
LOCAL_EDGES = 8_000_000


def from_actions(graph: BoostGraph) -> bool:
    """Are the graph's edges found from rows of actions (``sources.meetings``) rather than held?"""
    return "arrays" in graph.__dict__


def choose(graph: BoostGraph, strategy: str = "auto") -> str:
    """``local`` (adjacency in every worker) or ``relational`` (joins)."""
    if strategy not in ("auto", "local", "relational"):
        raise ValueError(strategy)
    if from_actions(graph):
        return "relational" if strategy == "relational" else "local"
    if strategy == "auto":
        return "local" if graph.m <= LOCAL_EDGES else "relational"
    if strategy == "local" and graph.m > LOCAL_EDGES:
        raise ValueError(f"{graph.m} edges are too many to send to every worker")
    return strategy


def adjacency(graph: BoostGraph) -> dict[str, np.ndarray]:
    """Compressed rows in both directions, as plain arrays; size checked by ``choose``."""
    if from_actions(graph):
        return {name: x for name, x in graph.arrays.items() if name != "rows"}
    edges = graph.edges.select("src", "dst", F.floor(F.col("p") * SPAN).cast("long").alias("tp"), F.floor(F.col("q") * SPAN).cast("long").alias("tq"))
    t = edges.limit(LOCAL_EDGES + 1).toArrow()
    if t.num_rows > LOCAL_EDGES:
        raise ValueError("too many edges to send to every worker")
    src, dst, tp, tq = (t.column(c).to_numpy() for c in ("src", "dst", "tp", "tq"))
    nodes = np.unique(np.concatenate([src, dst]))
    s, d = np.searchsorted(nodes, src), np.searchsorted(nodes, dst)
    out = {"nodes": nodes}
    for name, key, other in (("out", s, d), ("in", d, s)):
        order = np.lexsort((other, key))
        out |= {f"{name}_ptr": np.searchsorted(key[order], np.arange(len(nodes) + 1)), f"{name}_to": other[order], f"{name}_tp": tp[order], f"{name}_tq": tq[order]}
    return out


def sent(graph: BoostGraph):
    """The adjacency as a broadcast, made once for each graph and kept with it."""
    held = graph.__dict__.get("_sent")
    if held is None:
        held = graph.__dict__["_sent"] = graph.spark.sparkContext.broadcast(adjacency(graph))
    return held


def id_frame(spark, ids, name: str = "node") -> DataFrame:
    """Ids that the driver holds, as a frame to join with."""
    return spark.createDataFrame([(int(x),) for x in sorted(set(ids))], f"`{name}` long")


def positions(nodes: np.ndarray, ids: list[int]) -> np.ndarray:
    """Places of the ids that are nodes."""
    ids = np.array(sorted(set(ids)), np.int64)
    at = np.searchsorted(nodes, ids)
    good = at < len(nodes)
    return at[good][nodes[at[good]] == ids[good]]


def salted_join(left: DataFrame, right: DataFrame, on: str, heavy: DataFrame, salts: int = 16, how: str = "inner") -> DataFrame:
    """Join in which rows of ``left`` with a heavy key are dealt over ``salts`` partitions.

    ``heavy`` holds the heavy keys in a column named like ``on``; rows of
    ``right`` with such a key are repeated, all others stay single. Of more
    than 100,000 heavy keys the smallest are dealt; the rest join plainly.
    """
    mark = F.broadcast(heavy.select(on).distinct().orderBy(on).limit(100_000)).withColumn("_heavy", F.lit(True))
    spread = left.join(mark, on, "left").withColumn("_salt", F.when(F.col("_heavy"), F.pmod(F.monotonically_increasing_id(), F.lit(salts))).otherwise(0).cast("int")).drop("_heavy")
    copies = right.join(mark, on, "left").withColumn("_salt", F.explode(F.when(F.col("_heavy"), F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0))))).drop("_heavy")
    return spread.join(copies, [on, "_salt"], how).drop("_salt")

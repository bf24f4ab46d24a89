"""Simulation of the boosting diffusion, its spread, and exact enumeration."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import product

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nudgegraph.functions.coins import coin, threshold
from nudgegraph.model import BoostGraph
from nudgegraph.operators.kernels import Workspace, cascade, fan, helped, parts
from nudgegraph.plans.planner import choose, id_frame, positions, sent
from nudgegraph.session import Scratch

WORLD_MODES = ("receiver", "sender", "single_boost")


def _ids(frame: DataFrame | list[int] | None) -> list[int]:
    if frame is None:
        return []
    return [r.node for r in frame.select("node").distinct().collect()] if isinstance(frame, DataFrame) else list(frame)


def simulate(graph: BoostGraph, seeds, boost=None, worlds: int = 1000, salt: int = 1, mode: str = "receiver", coins: str = "fast", strategy: str = "auto", first: int = 0) -> DataFrame:
    """(world, node, step): when each node turns active in each world.

    Seeds are active at step 0. The same world has the same coins whatever is
    boosted, so that two calls can be compared world by world.
    """
    if mode not in WORLD_MODES:
        raise ValueError(mode)
    seed_ids, boost_ids = _ids(seeds), _ids(boost)
    run = _simulate_local if choose(graph, strategy) == "local" else _simulate_relational
    return run(graph, seed_ids, boost_ids, worlds, salt, mode, coins, first)


def _world_range(graph: BoostGraph, worlds: int, first: int) -> DataFrame:
    parts = max(1, min(worlds, 4 * graph.spark.sparkContext.defaultParallelism))
    return graph.spark.range(first, first + worlds, 1, parts).withColumnRenamed("id", "world")


def _placed(graph, seeds, boost):
    """The sent graph, places of seeds and boosted nodes, and seeds outside the graph: those have no edges but are active."""
    held = sent(graph)
    nodes = held.value["nodes"]
    s, b = positions(nodes, seeds), positions(nodes, boost)
    return held, s, b, np.array(sorted(set(seeds) - set(nodes[s].tolist())), np.int64)


def _simulate_local(graph, seeds, boost, worlds, salt, mode, coins, first) -> DataFrame:
    held, s, b, lone = _placed(graph, seeds, boost)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        g = held.value
        space = Workspace(len(g["nodes"]))
        for batch in batches:
            for world in batch.column(0).to_pylist():
                nodes, steps = cascade(g, s, b, world, salt, coins, mode, space)
                ids = np.concatenate([g["nodes"][nodes], lone])
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(ids), world)), pa.array(ids), pa.array(np.concatenate([steps, np.zeros(len(lone), np.int64)]).astype(np.int32))], ["world", "node", "step"])

    return _world_range(graph, worlds, first).mapInArrow(run, "world long, node long, step int")


#: bytes of worlds that a graph may keep: which nodes turn active where nothing is boosted
KEPT_WORLDS = 1 << 28


def _active(g: dict, s: np.ndarray, world: int, salt: int, coins: str, space: Workspace) -> np.ndarray:
    mask = np.zeros(len(g["nodes"]), bool)
    mask[cascade(g, s, s[:0], world, salt, coins, "receiver", space)[0]] = True
    return mask


def _unboosted(graph, held, s, worlds, salt, coins, first) -> DataFrame:
    """(world, bits): each world's active nodes if nothing is boosted; written once for each graph, seeds and setting.

    Where that is too much to keep there are no bits, and who reads the worlds finds them.
    """
    if worlds * (len(held.value["nodes"]) // 8 + 1) > KEPT_WORLDS:
        return _world_range(graph, worlds, first).withColumn("bits", F.lit(None).cast("binary"))
    kept, key = graph.__dict__.setdefault("_worlds", {}), (tuple(s.tolist()), worlds, salt, coins, first)
    if key not in kept:

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            g = held.value
            space = Workspace(len(g["nodes"]))
            for batch in batches:
                bits = [np.packbits(_active(g, s, world, salt, coins, space)).tobytes() for world in batch.column(0).to_pylist()]
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(bits, pa.binary())], ["world", "bits"])

        kept[key] = Scratch(graph.spark, "worlds").keep(_world_range(graph, worlds, first).mapInArrow(run, "world long, bits binary"), "bits")
    return kept[key]


def _counted_local(graph, seeds, arms, worlds, salt, coins, first) -> DataFrame:
    """(world, n0, n1, ...): active nodes of each world, one column for each arm (boosted nodes, mode)."""
    held, s, _, lone = _placed(graph, seeds, [])
    placed = [(positions(held.value["nodes"], boost), mode) for boost, mode in arms]
    some = any(mode == "receiver" for _, mode in placed)
    base = _unboosted(graph, held, s, worlds, salt, coins, first) if some else _world_range(graph, worlds, first).withColumn("bits", F.lit(None).cast("binary"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        g = held.value
        n, space = len(g["nodes"]), Workspace(len(g["nodes"]))
        for batch in batches:
            counts = [[] for _ in placed]
            for world, bits in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if some:
                    active = _active(g, s, world, salt, coins, space) if bits is None else np.unpackbits(np.frombuffer(bits, np.uint8), count=n).view(bool)
                    size = int(active.sum())
                for (b, mode), column in zip(placed, counts, strict=True):
                    found = size + helped(g, active, b, world, salt, coins, space) if mode == "receiver" else len(cascade(g, s, b, world, salt, coins, mode, space)[0])
                    column.append(found + len(lone))
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(c, pa.int64()) for c in counts]], ["world", *[f"n{i}" for i in range(len(counts))]])

    return base.mapInArrow(run, "world long" + "".join(f", n{i} long" for i in range(len(arms))))


def world_counts(graph: BoostGraph, seeds, arms: list[tuple], worlds: int, salt: int = 1, coins: str = "fast", strategy: str = "auto", first: int = 0) -> DataFrame:
    """(world, n0, n1, ...): active nodes of each world by arm (boosted nodes, mode), with the same coins in all arms."""
    seed_ids = _ids(seeds)
    arms = [(_ids(boost), mode) for boost, mode in arms]
    if any(mode not in WORLD_MODES for _, mode in arms):
        raise ValueError([mode for _, mode in arms])
    if choose(graph, strategy) == "local":
        return _counted_local(graph, seed_ids, arms, worlds, salt, coins, first)
    out = _world_range(graph, worlds, first)
    for i, (boost, mode) in enumerate(arms):
        n = world_spread(_simulate_relational(graph, seed_ids, boost, worlds, salt, mode, coins, first)).withColumnRenamed("n", f"n{i}")
        out = out.join(n, "world", "left").withColumn(f"n{i}", F.coalesce(f"n{i}", F.lit(0)))
    return out


def _simulate_relational(graph, seeds, boost, worlds, salt, mode, coins, first) -> DataFrame:
    spark, scratch = graph.spark, Scratch(graph.spark, "simulate")
    seed_frame = id_frame(spark, seeds)
    helped = id_frame(spark, boost, "helped").withColumn("boosted", F.lit(True))
    edges = graph.edges.join(helped, F.col("src" if mode == "sender" else "dst") == F.col("helped"), "left")
    edges = edges.select("src", "dst", threshold("p").alias("tp"), threshold("q").alias("tq"), F.coalesce("boosted", F.lit(False)).alias("boosted"))
    h = coin(coins, salt, "world", "src", "dst")
    front = scratch.keep(_world_range(graph, worlds, first).crossJoin(F.broadcast(seed_frame)).select("world", "node", F.lit(0).alias("layer"), F.lit(0).alias("step")), "front")
    settled, step = [front], 0
    while not front.isEmpty():
        step += 1
        met = front.select("world", F.col("node").alias("src"), "layer").join(edges, "src").withColumn("h", h)
        live, raised = F.col("h") < F.col("tp"), F.col("h") < F.col("tq")
        if mode == "single_boost":
            stay = met.where(live).select("world", F.col("dst").alias("node"), "layer")
            up = met.where(~live & raised & F.col("boosted") & (F.col("layer") == 0)).select("world", F.col("dst").alias("node"), F.lit(1).alias("layer"))
            reached = stay.unionByName(up)
        else:
            reached = met.where(F.when(F.col("boosted"), raised).otherwise(live)).select("world", F.col("dst").alias("node"), "layer")
        reached = reached.distinct()
        for old in settled:
            reached = reached.join(old.select("world", "node", "layer"), ["world", "node", "layer"], "left_anti")
        front = scratch.keep(reached.withColumn("step", F.lit(step)), "front")
        settled.append(front)
        if len(settled) > 8:
            whole = settled[0]
            for part in settled[1:]:
                whole = whole.unionByName(part)
            settled = [scratch.keep(whole, "settled")]
    whole = settled[0]
    for part in settled[1:]:
        whole = whole.unionByName(part)
    return whole.groupBy("world", "node").agg(F.min("step").cast("int").alias("step"))


def world_spread(active: DataFrame) -> DataFrame:
    """(world, n): active nodes by world."""
    return active.groupBy("world").agg(F.count("*").alias("n"))


def spread_mc(graph: BoostGraph, seeds, boost=None, runs: int = 20_000, mode: str = "receiver", **options) -> DataFrame:
    """One row (spread, stderr): mean active nodes over worlds."""
    n = world_counts(graph, seeds, [(boost, mode)], runs, **options)
    return n.agg(F.avg("n0").alias("spread"), (F.stddev_samp("n0") / F.sqrt(F.count("*"))).alias("stderr"))


def boost_mc(graph: BoostGraph, seeds, boost, runs: int = 20_000, mode: str = "receiver", **options) -> DataFrame:
    """One row (delta, stderr): mean gain over worlds with the same coins in both arms."""
    gain = world_counts(graph, seeds, [(boost, mode), (None, "receiver")], runs, **options).select((F.col("n0") - F.col("n1")).alias("gain"))
    return gain.agg(F.avg("gain").alias("delta"), (F.stddev_samp("gain") / F.sqrt(F.count("*"))).alias("stderr"))


def spread_exact(edges: list[tuple[int, int, float, float]], seeds: set[int], boost: set[int] = frozenset(), mode: str = "receiver", most: int = 12) -> float:
    """Expected spread of a tiny graph over all its worlds."""
    if len(edges) > most:
        raise ValueError(f"{len(edges)} edges have too many worlds")
    total = 0.0
    for states in product(*[[s for s, c in enumerate((p, q - p, 1 - q)) if c > 0] for _, _, p, q in edges]):
        chance, passable, lub = 1.0, [], []
        for (u, v, p, q), state in zip(edges, states, strict=True):
            chance *= (p, q - p, 1 - q)[state]
            if state == 0:
                passable.append((u, v))
            elif state == 1 and (u if mode == "sender" else v) in boost:
                lub.append((u, v))
        if chance:
            seen = {(s, 0) for s in seeds}
            now = list(seen)
            while now:
                x, layer = now.pop()
                new = [(v, layer) for u, v in passable if u == x]
                if mode == "single_boost":
                    new += [(v, 1) for u, v in lub if u == x and layer == 0]
                else:
                    new += [(v, layer) for u, v in lub if u == x]
                for y in new:
                    if y not in seen:
                        seen.add(y)
                        now.append(y)
            total += chance * len({v for v, _ in seen})
    return total


def spread_exact_of(graphs: DataFrame, shape: list[tuple], seeds: set[int], sets: list[tuple[int, ...]]) -> DataFrame:
    """(graph, boost, spread, delta): exact values of many tiny graphs of one shape, a row of ``graphs`` (graph, p) each.

    An edge of ``shape`` is (src, dst, place): its chance is the row's ``p`` at
    that place, raised with exponent 2, or one if the place is None.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for graph, p in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                edges = [(u, v, 1.0, 1.0) if at is None else (u, v, p[at], 1 - (1 - p[at]) * (1 - p[at])) for u, v, at in shape]
                rows += [(graph, " ".join(map(str, b)), spread_exact(edges, seeds, set(b)), boost_exact(edges, seeds, set(b))) for b in sets]
            if rows:
                columns = zip(*rows, strict=True)
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.string(), pa.float64(), pa.float64()), strict=True)], ["graph", "boost", "spread", "delta"])

    return graphs.select(F.col("graph").cast("long").alias("graph"), "p").mapInArrow(run, "graph long, boost string, spread double, delta double")


def boost_exact(edges, seeds: set[int], boost: set[int], **options) -> float:
    return spread_exact(edges, seeds, boost, **options) - spread_exact(edges, seeds)


#: nodes whose hops the driver may hold
LOCAL_HOPS = 200_000


def _hops_local(graph: BoostGraph, seeds: list[int], most: int | None, undirected: bool) -> DataFrame:
    g = sent(graph).value
    hops = np.full(len(g["nodes"]), -1, np.int32)
    front = positions(g["nodes"], seeds)
    hops[front], hop = 0, 0
    while (most is None or hop < most) and len(front):
        hop += 1
        before, front = front, []
        for way, rows in ((way, rows) for way in (("out", "in") if undirected else ("out",)) for rows in parts(before, g[f"{way}_ptr"])):
            front.append(np.unique(fan(g, way, rows, lambda to: hops[to] < 0)[0]))
            hops[front[-1]] = hop
        front = np.concatenate(front)
    found = hops >= 0
    lone = np.setdiff1d(np.array(sorted(set(seeds)), np.int64), g["nodes"])
    table = pa.table({"node": np.concatenate([g["nodes"][found], lone]), "hop": np.concatenate([hops[found], np.zeros(len(lone), np.int32)])})
    return graph.spark.createDataFrame(table, "node long, hop int")


def hop_layers(graph: BoostGraph, seeds: list[int], most: int | None = None, undirected: bool = False) -> DataFrame:
    """(node, hop): fewest edges from the seeds, which have hop 0."""
    if choose(graph) == "local" and graph.n <= LOCAL_HOPS:
        return _hops_local(graph, seeds, most, undirected)
    scratch = Scratch(graph.spark, "hops")
    edges = graph.edges.select("src", "dst")
    if undirected:
        edges = edges.unionByName(graph.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()
    seen = front = scratch.keep(graph.spark.createDataFrame([(x,) for x in sorted(set(seeds))], "node long").withColumn("hop", F.lit(0)), "hop")
    hop = 0
    while (most is None or hop < most) and not front.isEmpty():
        hop += 1
        new = front.select(F.col("node").alias("src")).join(edges, "src").select(F.col("dst").alias("node")).distinct().join(seen.select("node"), "node", "left_anti")
        front = scratch.keep(new.withColumn("hop", F.lit(hop)), "hop")
        seen = scratch.keep(seen.unionByName(front), "seen")
    return seen

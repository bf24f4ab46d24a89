"""Heuristics to compare with: weighted degrees and a reversed influence rank."""

from __future__ import annotations

import heapq

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nudgegraph.model import BoostGraph, BoostProblem
from nudgegraph.operators.diffusion import hop_layers
from nudgegraph.plans.planner import LOCAL_EDGES, choose, from_actions, id_frame
from nudgegraph.session import Scratch

KINDS = {1: "out", 2: "out_discounted", 3: "in_gain", 4: "in_gain_discounted"}


def degrees(problem: BoostProblem, kind: int) -> DataFrame:
    """(node, score) of all nodes but seeds: chance sent out (1, 2) or gained by a boost (3, 4)."""
    edges = problem.graph.edges
    scored = edges.select(F.col("src").alias("node"), F.col("p").alias("w")) if kind in (1, 2) else edges.select(F.col("dst").alias("node"), (F.col("q") - F.col("p")).alias("w"))
    summed = scored.groupBy("node").agg(F.sum("w").alias("score"))
    return problem.candidates().select("node").join(summed, "node", "left").select("node", F.coalesce("score", F.lit(0.0)).alias("score"))


def _pick(problem: BoostProblem, kind: int, k: int, scores: DataFrame, taken: list[int]) -> list[int]:
    """The k largest scores; discounted kinds lose, after each pick, the weights of edges that meet it."""
    order = [F.desc(F.round("score", 9)), F.col("node")]
    if kind in (1, 3):
        return [r.node for r in scores.orderBy(*order).limit(k).collect()]
    if choose(problem.graph) == "local" and not from_actions(problem.graph):
        return _pick_falling(_lost_weights(problem.graph, kind), k, scores, taken)
    edges, picked, spark = problem.graph.edges, [], problem.graph.spark
    gone = list(taken)
    while len(picked) < k:
        out, key = id_frame(spark, gone, "gone"), "dst" if kind == 2 else "src"
        met = edges.join(out, F.col(key) == F.col("gone"), "left_semi")
        lost = met.groupBy(F.col("src" if kind == 2 else "dst").alias("node")).agg(F.sum(F.col("p") if kind == 2 else F.col("q") - F.col("p")).alias("lost"))
        now = scores.join(out, F.col("node") == F.col("gone"), "left_anti").join(lost, "node", "left")
        top = now.select("node", (F.col("score") - F.coalesce("lost", F.lit(0.0))).alias("score")).orderBy(*order).first()
        if top is None:
            break
        picked.append(top.node)
        gone.append(top.node)
    return picked


def _lost_weights(graph: BoostGraph, kind: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(picked, loser, weight), ordered by the picked node: what its pick takes from whom; collected once a graph."""
    held = graph.__dict__.setdefault("_lost", {})
    if kind not in held:
        columns = ("dst", "src", F.col("p").alias("w")) if kind == 2 else ("src", "dst", (F.col("q") - F.col("p")).alias("w"))
        t = graph.edges.select(*columns).limit(LOCAL_EDGES).toArrow()
        key, other, w = (t.column(i).to_numpy() for i in range(3))
        order = np.lexsort((other, key))
        held[kind] = key[order], other[order], w[order]
    return held[kind]


def _pick_falling(lost: tuple[np.ndarray, np.ndarray, np.ndarray], k: int, scores: DataFrame, taken: list[int]) -> list[int]:
    """Scores only fall, and only those of a pick's neighbours: a heap in which outdated entries are passed over."""
    key, other, w = lost
    t = scores.select("node", "score").toArrow()
    now = dict(zip(t.column(0).to_pylist(), t.column(1).to_pylist(), strict=True))

    def neighbours(v: int):
        lo, hi = np.searchsorted(key, [v, v + 1])
        return zip(other[lo:hi].tolist(), w[lo:hi].tolist(), strict=True)

    for v in taken:
        now.pop(v, None)
        for u, x in neighbours(v):
            if u in now:
                now[u] -= x
    heap = [(-round(x, 9), v) for v, x in now.items()]
    heapq.heapify(heap)
    picked: list[int] = []
    while heap and len(picked) < k:
        score, v = heapq.heappop(heap)
        if v not in now or score != -round(now[v], 9):
            continue
        picked.append(v)
        del now[v]
        for u, x in neighbours(v):
            if u in now:
                now[u] -= x
                heapq.heappush(heap, (-round(now[u], 9), u))
    return picked


def degree_global(problem: BoostProblem, kind: int) -> list[int]:
    """k nodes of largest weighted degree, by one of the four definitions in ``KINDS``."""
    scratch = Scratch(problem.graph.spark, "degree")
    return _pick(problem, kind, problem.k, scratch.keep(degrees(problem, kind), "scores"), [])


def degree_local(problem: BoostProblem, kind: int, undirected: bool = False) -> list[int]:
    """As ``degree_global``, but all seeds' neighbours first, then what is two hops away, and so on."""
    scratch = Scratch(problem.graph.spark, "degree")
    hops = hop_layers(problem.graph, problem.seed_ids, undirected=undirected)
    scores = scratch.keep(degrees(problem, kind).join(hops, "node"), "scores")
    picked: list[int] = []
    layers = sorted(r.hop for r in scores.select("hop").distinct().collect())
    for hop in layers:
        if len(picked) >= problem.k:
            break
        picked += _pick(problem, kind, problem.k - len(picked), scores.where(F.col("hop") == hop).select("node", "score"), picked)
    return picked


def influence_rank(problem: BoostProblem, restart: float = 0.15, tol: float = 1e-4, rounds: int | None = None, most: int = 200) -> DataFrame:
    """(node, rank): stationary share of a walk against the direction of influence.

    From u the walk goes to v with chance p(v,u) over all that comes into u;
    nodes that nothing comes into spread their share evenly. With ``rounds``
    the number of steps is fixed, else it stops at a change of ``tol`` at most.
    """
    graph, scratch = problem.graph, Scratch(problem.graph.spark, "rank")
    n = graph.n
    into = graph.edges.groupBy(F.col("dst").alias("u")).agg(F.sum("p").alias("rho"))
    moves = scratch.keep(graph.edges.select(F.col("dst").alias("u"), F.col("src").alias("v"), "p").join(into, "u").select("u", "v", (F.col("p") / F.col("rho")).alias("w")), "moves")
    start = graph.nodes.select("node").join(into.select(F.col("u").alias("node"), F.lit(True).alias("in_")), "node", "left")
    rank = scratch.keep(start.select("node", F.col("in_").isNull().alias("sink"), F.lit(1.0 / n).alias("rank"), F.lit(0.0).alias("old")), "rank")
    for _ in range(rounds or most):
        seen = rank.agg(F.sum(F.abs(F.col("rank") - F.col("old"))).alias("change"), F.coalesce(F.sum(F.when(F.col("sink"), F.col("rank"))), F.lit(0.0)).alias("lost")).first()
        if rounds is None and seen.change <= tol:
            break
        flow = moves.join(rank.select(F.col("node").alias("u"), "rank"), "u").groupBy(F.col("v").alias("node")).agg(F.sum(F.col("w") * F.col("rank")).alias("flow"))
        base = restart / n + (1 - restart) * seen.lost / n
        new = rank.join(flow, "node", "left").select("node", "sink", (F.lit(base) + (1 - restart) * F.coalesce("flow", F.lit(0.0))).alias("rank"), F.col("rank").alias("old"))
        new = scratch.keep(new, "rank")
        scratch.drop(rank)
        rank = new
    return rank.select("node", "rank")


def influence_rank_pick(problem: BoostProblem, **options) -> list[int]:
    """The k nodes of highest rank but seeds; ranks know no seeds, so they are found once for each graph and setting and kept with the graph."""
    held, key = problem.graph.__dict__.setdefault("_ranks", {}), tuple(sorted(options.items()))
    if key not in held:
        held[key] = influence_rank(problem, **options)
    rank = held[key].join(problem.candidates().select("node"), "node", "left_semi")
    return [r.node for r in rank.orderBy(F.desc(F.round("rank", 9)), "node").limit(problem.k).collect()]


def hop_profile(problem: BoostProblem, boost: list[int]) -> DataFrame:
    """(hop, n): how far from the seeds the boosted nodes are; null if out of reach."""
    hops = hop_layers(problem.graph, problem.seed_ids)
    chosen = problem.graph.spark.createDataFrame([(v,) for v in boost], "node long")
    return chosen.join(hops, "node", "left").groupBy("hop").agg(F.count("*").alias("n"))

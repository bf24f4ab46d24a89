"""What larger tables showed: results that depended on a run's sample, divisions by zero, jobs too large."""

import math

import numpy as np
import pytest
from pyspark.errors import AnalysisException

from nudgegraph import catalogue
from nudgegraph.model import dense_nodes
from nudgegraph.operators import kernels
from nudgegraph.sources import networks as net
from nudgegraph.workloads import experiments, sampled


def test_node_numbers_do_not_depend_on_the_sampled_ranges(spark):
    edges = spark.range(0, 40_000, 1, 8).selectExpr("(id * 7919) % 40009 as src", "(id * 104729) % 40009 as dst")
    options = {"spark.sql.execution.rangeExchange.sampleSizePerPartition": "2", "spark.sql.adaptive.coalescePartitions.enabled": "false"}
    for name, value in options.items():
        spark.conf.set(name, value)
    try:
        rows = dense_nodes(edges).orderBy("node").collect()
    finally:
        for name in options:
            spark.conf.unset(name)
    assert [r.idx for r in rows] == list(range(len(rows))) and len(rows) > 40_000


def test_ratio_without_a_boost(spark, duck, monkeypatch):
    monkeypatch.setattr(sampled, "_estimates", lambda s, d: s.createDataFrame([(0.0, 0.0)], "delta double, mu double"))
    want = duck.sql("select round(round(0.0::double, 6) / round(0.0::double, 6), 5)").fetchall()[0][0]
    assert math.isnan(want) and math.isnan(sampled._ratio(spark, None).first().ratio)


def test_ratio_check_of_a_network_without_boosts(spark, monkeypatch):
    def w07(s, d, grid):
        return experiments._table(s, [experiments._row("w07", "ratio", 1.0, net=grid.nets[0], k=k) for k in grid.ks])

    monkeypatch.setattr(experiments, "w07", w07)
    assert all(all(r[1:]) for r in experiments._ratio(spark, None).collect())


READ_A_TABLE = ["exact_spread_cover", "exact_spread_gate", "exact_spread_path", "exact_spread_star", "exp_worked_examples", "required_sketches", "sink_run_log", "source_binary_tree", "source_literal", "tree_dp_binary_r", "tree_dp_exact_r"]


@pytest.mark.parametrize("name", READ_A_TABLE)
def test_reads_a_table(spark, name):
    with pytest.raises(AnalysisException, match="PATH_NOT_FOUND"):
        catalogue.QUERIES[name](spark, "/no/such/folder").collect()


def test_coins_of_settled_nodes_are_not_drawn(monkeypatch):
    """On a dense graph a search draws far fewer coins than edges, and finds what all coins give."""
    n, coins, drawn = 400, kernels.coin_array, []
    a, b = (x.ravel() for x in np.divmod(np.arange(n * n), n))
    a, b = a[a != b], b[a != b]
    p = np.full(len(a), int(0.05 * 2**32))
    ptr = np.arange(n + 1) * (n - 1)
    g = {"nodes": np.arange(n) * 3, "out_ptr": ptr, "out_to": b, "out_tp": p, "out_tq": 2 * p, "in_ptr": ptr, "in_to": b, "in_tp": p, "in_tq": 2 * p}
    monkeypatch.setattr(kernels, "coin_array", lambda mode, salt, *ids: drawn.append(len(ids[-1])) or coins(mode, salt, *ids))
    monkeypatch.setattr(kernels, "EDGES_AT_ONCE", 4000)
    for world in range(5):
        forth = coins("fast", 1, world, 3 * a, 3 * b)
        live = {"forth": forth < np.where(b < 9, 2 * p, p), "back": coins("fast", 1, world, 3 * b, 3 * a) < p}
        for which, run in (("forth", lambda: kernels.cascade(g, np.array([5]), np.arange(9), world, 1, "fast", "receiver")), ("back", lambda: (kernels.reach_set(g, 5, world, 1, "fast"), None))):
            step = np.full(n, -1)
            step[5], t = 0, 0
            while (step == t).any():
                new = b[live[which] & (step[a] == t)]
                t += 1
                step[new[step[new] < 0]] = t
            nodes, steps = run()
            assert np.sort(nodes).tolist() == np.flatnonzero(step >= 0).tolist() if which == "forth" else nodes.tolist() == np.flatnonzero(step >= 0).tolist()
            assert steps is None or steps.tolist() == step[step >= 0].tolist()
    assert sum(drawn) < 0.5 * 10 * len(a)


def test_edge_files_do_not_pile_up(spark, sf, monkeypatch):
    """Each format goes once the next is written; text formats are compressed."""
    from pathlib import Path

    from nudgegraph.workloads import toolkit

    paths = []
    monkeypatch.setattr(toolkit, "scratch_path", lambda s, tag, make=toolkit.scratch_path: paths.append(make(s, tag)) or paths[-1])
    rows = catalogue.QUERIES["source_edge_files"](spark, sf)
    left = [p for p in map(Path, (p.removeprefix("file://") for p in paths)) if p.exists()]
    assert len(paths) == 4 and [p.name.split("-")[1] for p in left] == ["json"] and list(left[0].glob("*.json.gz")) and rows.count() > 0


def test_learned_edges_move_once(spark, sf):
    """Nothing is joined to the edges after they were counted."""
    from pyspark.sql import functions as F

    plan = catalogue.QUERIES["net_events_48h"](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("Aggregate") < plan.index("Join")
    actions = spark.createDataFrame([(1, "a", 0), (2, "a", 60), (1, "b", 0), (None, "a", 30), (3, "c", 0)], "actor long, action string, s long").select("actor", "action", F.timestamp_seconds("s").alias("ts"))
    assert [tuple(r) for r in net.learn_probabilities(actions, None, "1 hour").collect()] == [(1, 2, 0.5)]


def test_cover_comes_to_the_driver_once_the_rest_fits(spark, monkeypatch):
    """A cover whose first picks leave little makes no job a pick to its end; picks are those of plain sets."""
    import random

    from nudgegraph.plans import stopping

    rng = random.Random(4)
    rows = [(s, v) for s in range(300) for v in {rng.randrange(40), rng.randrange(40), 40 if s < 250 else 41}]
    df, lists = spark.createDataFrame(rows + rows[:5], "sketch long, node long"), {}
    for s, v in rows:
        lists.setdefault(v, set()).add(s)
    want, covered = [], set()
    while len(want) < 9 and any(x - covered for x in lists.values()):
        best = max(lists, key=lambda v: (len(lists[v] - covered), -v))
        want.append((best, len(lists[best] - covered)))
        covered |= lists[best]
    local, held = stopping._cover_arrays, []
    monkeypatch.setattr(stopping, "_cover_arrays", lambda s, v, k: held.append(k) or local(s, v, k))
    monkeypatch.setattr(stopping, "LOCAL_POSTINGS", 200)
    assert stopping.cover_greedy(df, 9) == want and held and 0 < held[0] < 9
    assert local(np.array([s for s, _ in rows]), np.array([v for _, v in rows]), 9) == want
    assert stopping.cover_greedy(df.where("sketch < 0"), 3) == [] and stopping.cover_greedy(df, 0) == []


def test_marginal_picks_on_the_driver_equal_recounts(spark, monkeypatch):
    import random

    from nudgegraph.model import BoostGraph
    from nudgegraph.operators import sketches

    rng = random.Random(8)
    rows = sorted({(a, b): (a, b, 0.15, 0.5) for a, b in ((rng.randrange(30), rng.randrange(30)) for _ in range(140)) if a != b}.values())
    drawn = sketches.sample_sketches(BoostGraph.from_edges(spark.createDataFrame(rows, "src long, dst long, p double, q double")), [0, 1], 0, 400, 4).cache()
    monkeypatch.setattr(sketches, "marginal_counts", lambda *a, f=sketches.marginal_counts: jobs.append(a) or f(*a))
    jobs = []
    got = sketches.select_marginal(drawn, 6, [0, 1, 2])
    assert len(got) == 6 and not jobs
    monkeypatch.setattr(sketches, "LOCAL_SKETCH_EDGES", 0)
    assert sketches.select_marginal(drawn, 6, [0, 1, 2]) == got and len(jobs) == 6


def test_hops_on_the_driver_equal_joins(spark, monkeypatch):
    from nudgegraph.model import BoostGraph
    from nudgegraph.operators import diffusion

    rows = [(a, (a * 7 + j) % 60, 0.1, 0.2) for a in range(0, 60, 2) for j in range(1, 3) if a != (a * 7 + j) % 60]
    graph = BoostGraph.from_edges(spark.createDataFrame(rows, "src long, dst long, p double, q double"))
    asked = [([3, 4, 999], None, False), ([4], 2, False), ([4], None, True), ([], None, False)]
    near = [sorted(map(tuple, diffusion.hop_layers(graph, *a).collect())) for a in asked]
    assert graph.__dict__.get("_sent") is not None
    monkeypatch.setattr(diffusion, "LOCAL_HOPS", 0)
    assert near == [sorted(map(tuple, diffusion.hop_layers(graph, *a).collect())) for a in asked]


def small_graph(spark):
    from nudgegraph.model import BoostGraph

    rows = [(a, (a * 5 + j) % 40, 0.2, 0.36) for a in range(40) for j in range(1, 4) if a != (a * 5 + j) % 40]
    return BoostGraph.from_edges(spark.createDataFrame(rows, "src long, dst long, p double, q double"))


def test_seeds_are_found_once_a_graph(spark, monkeypatch):
    from nudgegraph.plans import solvers

    found = []
    monkeypatch.setattr(solvers, "reach_sets", lambda *a, f=solvers.reach_sets: found.append(a) or f(*a))
    graph = small_graph(spark)
    first = solvers.seeds_influential(graph, 3, theta=200)
    first.append(-1)
    assert solvers.seeds_influential(graph, 3, theta=200) == first[:-1] and len(found) == 1
    assert solvers.seeds_influential(graph, 3, theta=300) and len(found) == 2
    assert solvers.seeds_influential(small_graph(spark), 3, theta=200) == first[:-1] and len(found) == 3


def test_sets_are_judged_in_one_job(spark, monkeypatch):
    from nudgegraph.model import BoostProblem, RunReport, Solution
    from nudgegraph.operators.diffusion import boost_mc
    from nudgegraph.plans import solvers

    problem, jobs = BoostProblem(small_graph(spark), spark.createDataFrame([(0,), (1,)], "node long"), 3), []
    sets = [[5], [7, 6], [6, 7], [], [8, 9, 10]]
    values = [boost_mc(problem.graph, [0, 1], b, 100).first().delta for b in sets]
    monkeypatch.setattr(solvers, "world_counts", lambda g, s, arms, *a, f=solvers.world_counts, **o: jobs.append(len(arms)) or f(g, s, arms, *a, **o))
    got = solvers.best_of(problem, [Solution(b, RunReport({})) for b in sets], 100)
    assert got.boost == sets[max(range(5), key=lambda i: (values[i], -i))] and jobs == [5]


def test_exponents_share_edges_and_seeds(spark, monkeypatch):
    from dataclasses import replace

    made, asked = [], []
    monkeypatch.setattr(experiments, "network", lambda s, d, name, beta=2.0: made.append(beta) or small_graph(s))
    monkeypatch.setattr(experiments, "_seeds", lambda g, grid, mode, f=experiments._seeds: asked.append(f(g, grid, mode)) or asked[-1])
    grid = replace(experiments.SMALL, nets=("x",), ks=(2,), theta=100, runs=20)
    rows = experiments.w08(spark, None, grid).collect()
    assert len(made) == len(asked) == 1 and {r.beta for r in rows} == {2.0, 4.0}


@pytest.mark.parametrize("name", ["exp_boost_vs_k_p", "exp_random_seeds_p"])
def test_both_networks_are_compared(spark, duck, monkeypatch, name):
    """With random seeds as with influential ones, in the query and in its SQL."""

    def compare(s, d, exp, grid, modes, methods):
        rows = [experiments._row(exp, "boost", k, net=n, solver=m, mode=modes[0], k=k) for n in grid.nets for m in methods for k in grid.ks]
        return experiments._table(s, rows)

    monkeypatch.setattr(experiments, "compare", compare)
    got = [tuple(r) for r in experiments.QUERIES[name](spark, None).collect()]
    assert sorted(got) == sorted(duck.sql(experiments.ORACLES[name]).fetchall()) and [r[0] for r in got] == list(experiments.SMALL.nets)


def test_compression_follows_the_sampling_rule(spark, monkeypatch):
    """Seeds and sketches of every solve come from the rule, not from a given number."""
    from nudgegraph.model import BoostGraph
    from nudgegraph.plans import solvers

    rows = [(u, (u * 7 + i) % 30, 0.05, 0.4) for u in range(30) for i in (1, 2, 5) if (u * 7 + i) % 30 != u]
    graph = BoostGraph.from_edges(spark.createDataFrame(rows, "src long, dst long, p double, q double"))
    ruled = []
    monkeypatch.setattr(experiments, "network", lambda s, d, name: graph)
    monkeypatch.setattr(experiments, "SMALL", experiments.replace(experiments.SMALL, seeds=2, ks=(2, 3), runs=20))
    monkeypatch.setattr(solvers, "run_martingale", lambda *a, f=solvers.run_martingale: ruled.append(f(*a)) or ruled[-1])
    assert tuple(experiments._compress(spark, None).first()) == (True, True, True)
    assert len(ruled) == 6 and all(x.certified for x in ruled)


def test_what_knows_no_seeds_is_found_once(spark, monkeypatch):
    """Ranks and reach sets of a graph serve all its problems, with the picks of a graph that keeps nothing."""
    from nudgegraph.model import BoostGraph, BoostProblem
    from nudgegraph.operators import baselines
    from nudgegraph.plans import solvers

    rows = [(u, (u * 7 + i) % 30, 0.1, 0.4) for u in range(30) for i in (1, 2, 5) if (u * 7 + i) % 30 != u]
    edges = spark.createDataFrame(rows, "src long, dst long, p double, q double")
    calls = []
    monkeypatch.setattr(baselines, "influence_rank", lambda *a, f=baselines.influence_rank, **o: calls.append("rank") or f(*a, **o))
    monkeypatch.setattr(solvers, "reach_sets", lambda *a, f=solvers.reach_sets: calls.append("reach") or f(*a))
    one, got, want = BoostGraph.from_edges(edges), [], []
    for graphs, out in (([one, one], got), ([BoostGraph.from_edges(edges), BoostGraph.from_edges(edges)], want)):
        for g, seeds, k in zip(graphs, ([0], [4, 9]), (2, 3), strict=True):
            p = BoostProblem(g, spark.createDataFrame([(s,) for s in seeds], "node long"), k)
            out += [solvers.solve(p, "influence_rank", rounds=2).boost, solvers.solve(p, "extra_seeds", theta=100).boost]
        calls.append("next")
    assert got == want and calls == ["rank", "reach", "next", *["rank", "reach"] * 2, "next"]

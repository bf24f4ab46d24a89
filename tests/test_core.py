import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from nudgegraph.functions.coins import coin, coin_array, root_array, root_coin
from nudgegraph.model import EDGES, SUPER, BoostGraph, BoostProblem, assert_schema, dense_nodes, with_boost
from nudgegraph.operators import diffusion, kernels, sketches
from nudgegraph.operators.components import components
from nudgegraph.plans import planner, solvers, stopping
from nudgegraph.sources import networks as net
from nudgegraph.sources.tables import literal_graph
from nudgegraph.workloads.sampled import COVER, GATE, PATH, STAR


def random_graph(rng, n, m):
    pairs = rng.sample([(a, b) for a in range(n) for b in range(n) if a != b], m)
    return [(a, b, p, 1 - (1 - p) ** 2) for (a, b), p in zip(pairs, (rng.choice([0.2, 0.4, 0.6]) for _ in pairs), strict=True)]


@pytest.fixture(scope="module")
def events(spark, sf):
    return BoostGraph(BoostGraph.from_edges(net.net_events(spark, sf)).edges.cache())


def test_coins_have_twins(spark):
    df = spark.range(40).select(F.col("id").alias("w"), (F.col("id") * 7 - 3).alias("a"), (F.col("id") * 11).alias("b"))
    for mode in ("fast", "portable"):
        rows = df.select("w", "a", "b", coin(mode, 7, "w", "a", "b").alias("h"), root_coin(mode, 7, "w").alias("r")).collect()
        ids = [np.array([r[i] for r in rows]) for i in range(3)]
        assert [r.h for r in rows] == coin_array(mode, 7, *ids).tolist()
        assert [r.r for r in rows] == root_array(mode, 7, ids[0]).tolist()
    assert coin_array("portable", 7, 1, 2, 3).item() == 250874271


@pytest.mark.parametrize(
    ("edges", "seeds", "boost", "spread"),
    [(PATH, {0}, (), 1.22), (PATH, {0}, (1,), 1.44), (PATH, {0}, (2,), 1.24), (PATH, {0}, (1, 2), 1.48), (STAR, {1, 3}, (), 2.209), (STAR, {1, 3}, (0,), 2.37829), (STAR, {1, 3}, (0, 2), 2.409241), (COVER, {0}, (), 6.25), (COVER, {0}, (1, 3), 9.5), (GATE, {0}, (3,), 2.75)],
)
def test_worked_examples(edges, seeds, boost, spread):
    assert abs(diffusion.spread_exact(edges, seeds, set(boost)) - spread) < 1e-9


def test_at_most_one_boosted_edge():
    mu = lambda b: diffusion.boost_exact(PATH, {0}, b, mode="single_boost")
    assert abs(mu({1}) - 0.22) < 1e-9 and abs(mu({2}) - 0.02) < 1e-9 and abs(mu({1, 2}) - 0.24) < 1e-9
    # neither submodular nor supermodular
    parallel = [(0, 1, 0.2, 0.4), (0, 2, 0.2, 0.4), (1, 3, 1.0, 1.0), (2, 3, 1.0, 1.0)]
    d = lambda b: diffusion.boost_exact(parallel, {0}, b)
    assert d({1, 2}) < d({1}) + d({2}) and diffusion.boost_exact(PATH, {0}, {1, 2}) > diffusion.boost_exact(PATH, {0}, {1}) + diffusion.boost_exact(PATH, {0}, {2})


def test_sampled_states_example():
    """A sketch with known states: 9 nodes and 13 edges are found, 6 nodes and 7 edges remain."""
    r = 20
    live = [(0, r), (1, r), (2, r), (3, 0), (6, 4), (7, 4), (8, 2)]
    lub = [(2, 1), (4, 1), (5, 2), (4, 3), (1, 5), (7, 5), (7, 6), (10, 7)]
    raw = [(u, v, True) for u, v in live] + [(u, v, False) for u, v in lub if (u, v) != (10, 7)]
    edges, critical = kernels.compress(r, raw, {7, 9}, 5)
    assert critical == [1, 3]
    assert set(edges) == {(SUPER, 1, False), (SUPER, 3, False), (SUPER, 5, False), (5, 2, False), (1, r, True), (2, r, True), (3, r, True)}
    for boost, hit in (((), 0), ((1,), 1), ((3,), 1), ((2, 5), 1), ((2,), 0), ((5,), 0)):
        assert kernels.activates(r, edges, set(boost)) == bool(hit)
    assert kernels.marginal_nodes(r, edges, set()) == [1, 3] and kernels.marginal_nodes(r, edges, {5}) == [1, 2, 3] and kernels.marginal_nodes(r, edges, {1}) == []


def test_simulation_matches_enumeration(spark):
    g = BoostGraph.from_edges(literal_graph(spark, STAR))
    r = diffusion.spread_mc(g, [1, 3], [0, 2], 20_000).first()
    assert abs(r.spread - 2.409241) < 5 * r.stderr
    d = diffusion.boost_mc(g, [1, 3], [0], 20_000).first()
    assert abs(d.delta - 0.16929) < 5 * d.stderr


@pytest.mark.parametrize("mode", diffusion.WORLD_MODES)
def test_simulation_forms_agree(events, mode):
    seeds, boost = solvers.seeds_random(events, 3), solvers.seeds_random(events, 3, 1)
    a, b = (sorted(map(tuple, diffusion.simulate(events, seeds, boost, 6, 1, mode, "fast", how).collect())) for how in ("local", "relational"))
    assert a == b


@pytest.mark.parametrize("coins", ["fast", "portable"])
def test_sketch_forms_agree(events, coins):
    seeds = solvers.seeds_random(events, 2)
    a, b = (sorted(map(repr, sketches.sample_sketches(events, seeds, 0, 30, 3, 1, coins, how).collect())) for how in ("local", "relational"))
    assert a == b
    a, b = (sorted(map(tuple, sketches.reach_sets(events, 0, 20, 1, coins, how).collect())) for how in ("local", "relational"))
    assert a == b


def test_estimates_are_unbiased(spark):
    rng = random.Random(4)
    rows = random_graph(rng, 6, 9)
    g, theta = BoostGraph.from_edges(literal_graph(spark, rows)), 6000
    k = sketches.sample_sketches(g, [0], 0, theta, 6).cache()
    for boost in ({1}, {2, 3}, {1, 4, 5}):
        exact, bound = diffusion.boost_exact(rows, {0}, boost), diffusion.boost_exact(rows, {0}, boost, mode="single_boost")
        delta, mu, nu = (f(k, sorted(boost), g.n, theta) for f in (sketches.delta_hat, sketches.mu_hat, sketches.nu_hat))
        assert mu <= delta <= nu and abs(delta - exact) < 0.15 and abs(mu - bound) < 0.15


def test_compression_keeps_every_set(events):
    seeds = solvers.seeds_random(events, 2)
    sets = [[], solvers.seeds_random(events, 5, 2), solvers.seeds_random(events, 3, 3)]
    assert sketches.equivalence_faults(events, seeds, 0, 300, 5, sets) == 0


def test_solvers_against_exhaustion(spark):
    rng = random.Random(9)
    for _ in range(2):
        rows = random_graph(rng, 6, 9)
        p = BoostProblem(BoostGraph.from_edges(literal_graph(spark, rows)), spark.createDataFrame([(0,)], "node long"), 2)
        _, best = solvers.solve_bruteforce(rows, {0}, 2)
        for method in ("sketch_full", "sketch_critical", "sandwich"):
            s = solvers.solve(p, method, theta=4000)
            assert len(s.boost) <= 2 and 0 not in s.boost
            assert diffusion.boost_exact(rows, {0}, set(s.boost)) >= 0.6 * best


def test_stopping_constants():
    # the bound equals its other published form
    n, k, eps, ell, opt = 1497, 10, 0.5, 1.0, 10.0
    a = math.sqrt(ell * math.log(n) + math.log(2))
    b = math.sqrt((1 - 1 / math.e) * (stopping.log_choose(n, k) + ell * math.log(n) + math.log(2)))
    assert stopping.required_sketches(n, k, eps, ell, opt) == math.ceil(2 * n * ((1 - 1 / math.e) * a + b) ** 2 / eps**2 / opt)
    assert abs(3 * 1000 ** -stopping.inflate_ell(1.0, 1000) - 1000**-1.0) < 1e-9


def test_cover_forms_agree(spark, monkeypatch):
    rng = random.Random(2)
    df = spark.createDataFrame([(s, rng.randrange(12)) for s in range(60) for _ in range(3)], "sketch long, node long").distinct().cache()
    lazy = stopping.cover_greedy(df, 5)
    monkeypatch.setattr(stopping, "LOCAL_POSTINGS", 1)
    assert stopping.cover_greedy(df, 5) == lazy


def test_components(spark):
    rng = random.Random(1)
    edges = [(rng.randrange(80), rng.randrange(80)) for _ in range(50)] + [(200 + i, 201 + i) for i in range(40)] + [(None, 1), (5, 5)]
    up = list(range(300))

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for a, b in edges:
        if a is not None:
            x, y = root(a), root(b)
            up[max(x, y)] = min(x, y)
    got = {r.node: r.component for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got and all(root(v) == c for v, c in got.items()) and components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_model(spark, events):
    nodes = dense_nodes(events.edges).orderBy("node").collect()
    assert [r.idx for r in nodes] == list(range(len(nodes)))
    with pytest.raises(TypeError):
        assert_schema(spark.createDataFrame([(1,)], "src int"), EDGES)
    q = {b: with_boost(spark.createDataFrame([(0.3,)], "p double"), b).first().q for b in (1.0, 2.0, 2.5)}
    assert abs(q[1.0] - 0.3) < 1e-12 and abs(q[2.0] - 0.51) < 1e-12 and abs(q[2.5] - (1 - 0.7**2.5)) < 1e-12
    with pytest.raises(ValueError):
        planner.choose(events, "other")


def test_plans(events):
    """Coins are judged before any exchange; a front joins edges by equality; nothing is a product."""
    from nudgegraph.functions.coins import threshold

    front = events.spark.range(10).select(F.col("id").alias("world"), F.col("id").alias("src"))
    hit = front.join(events.edges.select("src", "dst", threshold("p").alias("tp")), "src").where(coin("fast", 1, "world", "src", "dst") < F.col("tp")).groupBy("world").count()
    plan = hit._jdf.queryExecution().executedPlan().toString()
    assert "HashJoin" in plan or "SortMergeJoin" in plan
    assert "CartesianProduct" not in plan and "BatchEvalPython" not in plan and plan.index("HashAggregate") < plan.index("Join")

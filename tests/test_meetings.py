"""A network of actions gives the same whether its edges are held or found from the actions."""

import pytest
from pyspark.sql import functions as F

from nudgegraph.model import BoostGraph
from nudgegraph.operators import diffusion, kernels
from nudgegraph.operators.baselines import degree_global
from nudgegraph.operators.diffusion import hop_layers, simulate, world_counts
from nudgegraph.operators.sketches import reach_sets, sample_sketches
from nudgegraph.plans.planner import choose
from nudgegraph.sources import meetings
from nudgegraph.sources import networks as net
from nudgegraph.workloads.networks import graph_stats, largest_wcc


def rows_of(frame):
    return sorted(tuple(r) for r in frame.collect())


@pytest.fixture
def both(spark, monkeypatch):
    """Two groups of actors with actions of their own; ties in time, actors who meet nobody, nulls."""
    import random

    rng = random.Random(3)
    rows = {(100 * part + a, f"{part}-{rng.randrange(6)}"): rng.randrange(0, 90_000, 300) for part, size in ((1, 20), (2, 35)) for a in range(size) for _ in range(9)}
    log = [(a, x, t) for (a, x), t in rows.items()] + [(900, "alone", 5), (None, "1-1", 600), (101, None, 600), (102, "no time", None)]
    actions = spark.createDataFrame(log, "actor long, action string, s long").select("actor", "action", F.timestamp_seconds("s").alias("ts"))
    held = meetings.action_graph(actions, "6 hours", 2.0)
    monkeypatch.setattr(meetings, "LOCAL_EDGES", 0)
    found = meetings.action_graph(actions, "6 hours", 2.0)
    assert type(held) is BoostGraph and type(found) is meetings.MeetingGraph
    return held, found


def test_edges_and_nodes(both):
    held, found = both
    assert rows_of(held.edges) == rows_of(found.edges) and rows_of(held.nodes) == rows_of(found.nodes)
    assert (held.n, held.m) == (found.n, found.m) and found.measures[1] == pytest.approx(held.edges.agg(F.avg("p")).first()[0])


def test_largest_component(both):
    held, found = both
    want = largest_wcc(held.edges)
    got = found.largest()
    assert rows_of(got.edges) == rows_of(want) and 30 < got.n < found.n
    s = graph_stats(want).first()
    assert (got.n, got.m, round(got.measures[1], 6)) == (s.n, s.m, s.avg_p)
    sets = [reach_sets(g, 0, 40) for g in (BoostGraph(want), got)]
    assert rows_of(sets[0]) == rows_of(sets[1])


@pytest.mark.parametrize("dense", [0.25, 0.0])
def test_searches(both, spark, monkeypatch, dense):
    """Also where a front is looked for by the nodes that it may reach, on the driver as in the workers."""
    held, found = both
    seeds, boost = [100, 203, 210, 5], [104, 205, 211, 212, 230]
    for mode in ("receiver", "sender", "single_boost"):
        a, b = (simulate(g, seeds, boost, 12, mode=mode, coins="portable") for g in both)
        assert rows_of(a) == rows_of(b)
    for run in (lambda g: reach_sets(g, 0, 40), lambda g: sample_sketches(g, seeds[:2], 0, 40, 2), lambda g: hop_layers(g, seeds)):
        assert rows_of(run(held)) == rows_of(run(found))
    from nudgegraph.plans.planner import sent

    monkeypatch.setattr(kernels, "DENSE", dense)
    for met, least in ((0, 0.05), (1, 0.5), (32, -1.0)):
        monkeypatch.setattr(kernels, "MET_TRIED", met)
        monkeypatch.setattr(kernels, "LEAST_FOUND", least)
        monkeypatch.setattr(kernels, "EDGES_AT_ONCE", 50)
        a, b = (sent(g).value for g in both)
        place = kernels.np.array([0, 30])
        for world in range(8):
            x, y = (kernels.cascade(g, place, place + 5, world, 1, "fast", "receiver") for g in (a, b))
            assert x[0].tolist() == y[0].tolist() and x[1].tolist() == y[1].tolist()
            assert kernels.reach_set(a, 30, world, 1, "fast").tolist() == kernels.reach_set(b, 30, world, 1, "fast").tolist()


def test_baselines_read_all_edges(both, spark):
    from nudgegraph.model import BoostProblem

    picks = [degree_global(BoostProblem(g, spark.createDataFrame([(100,)], "node long"), 5), kind) for g in both for kind in (2, 4)]
    assert picks[:2] == picks[2:] and all(len(p) == 5 for p in picks)


@pytest.mark.parametrize("framework", ["martingale", "doubling"])
def test_as_many_seeds_as_asked_for(spark, framework):
    """One node covers every sample: the others make up the number."""
    from nudgegraph.plans.solvers import allocate_budget, seeds_influential

    rows = [(7, v, 1.0, 1.0) for v in (1, 2, 3)]
    graph = BoostGraph.from_edges(spark.createDataFrame(rows, "src long, dst long, p double, q double"))
    assert seeds_influential(graph, 3, framework=framework) == [7, 1, 2] and len(seeds_influential(graph, 9, framework=framework)) == 4
    assert seeds_influential(graph, 3, theta=50) == [7]
    assert allocate_budget(graph, 2, 3, (1.0,), 5).first().n_seeds == 2


def test_postings_told_to_be_unique_are_counted_where_they_are(spark, monkeypatch):
    from nudgegraph.plans import stopping

    rows = sorted({(s, v) for s in range(60) for v in (s % 7, s % 11, 20 + s % 2)})
    df, kept = spark.createDataFrame(rows, "sketch long, node long"), []
    want = stopping.cover_greedy(df, 6)
    monkeypatch.setattr(stopping, "LOCAL_POSTINGS", 40)
    monkeypatch.setattr(stopping.Scratch, "keep", lambda self, d, name, f=stopping.Scratch.keep: kept.append(name) or f(self, d, name))
    plain, n = stopping.cover_greedy(df, 6), len(kept)
    assert plain == want == stopping.cover_greedy(df, 6, unique=True) and len(kept) == 2 * n - 1


@pytest.mark.parametrize("name", ["spread_mc_r", "boost_mc_r", "activation_steps_r", "seeds_doubling_p", "pure_seeding_p"])
def test_queries_list_no_edge(spark, sf, monkeypatch, name):
    """Of a network whose meetings are many no edge is written, and the result is the same."""
    from nudgegraph import catalogue

    want = rows_of(catalogue.QUERIES[name](spark, sf))
    monkeypatch.setattr(meetings, "LOCAL_EDGES", 0)
    monkeypatch.setattr(meetings.MeetingGraph, "listed", lambda self: pytest.fail("edges are listed"))
    assert rows_of(catalogue.QUERIES[name](spark, sf)) == want


def test_what_the_actions_do_not_allow(spark, monkeypatch):
    """More actions than may be sent: edges are joined as before, and the choice is by their number."""
    actions = spark.createDataFrame([(1, "a", 0), (2, "a", 60), (3, "a", 120)], "actor long, action string, s long").select("actor", "action", F.timestamp_seconds("s").alias("ts"))
    monkeypatch.setattr(meetings, "LOCAL_EDGES", 0)
    graph = meetings.action_graph(actions, "1 hour")
    assert choose(graph) == "local" and choose(graph, "relational") == "relational" and graph.m == 3
    monkeypatch.setattr(meetings, "LOCAL_ACTIONS", 2)
    other = meetings.action_graph(actions, "1 hour")
    assert type(other) is BoostGraph and rows_of(other.edges) == rows_of(graph.edges)
    assert net.learn_probabilities(actions, None, "1 hour").count() == 3


def test_preparation_finds_each_network_once(spark, sf, monkeypatch):
    """A network's edges are made once and read from a table after that; the one of events lists none."""
    from nudgegraph.workloads import experiments

    made, kept = [], []
    monkeypatch.setattr(experiments.Scratch, "keep", lambda self, d, name, f=experiments.Scratch.keep: kept.append((name, d)) or f(self, d, name))
    monkeypatch.setattr(experiments, "largest_wcc", lambda e, f=experiments.largest_wcc: made.append(e.inputFiles()) or f(e))
    want = rows_of(experiments._preparation(spark, sf))
    assert len(made) == 4 and all("whole" in files[0] for files in made)
    monkeypatch.setattr(meetings, "LOCAL_EDGES", 0)
    monkeypatch.setattr(meetings.MeetingGraph, "listed", lambda self: pytest.fail("edges are listed"))
    assert rows_of(experiments._preparation(spark, sf)) == want and len(made) == 7
    assert rows_of(experiments._cost_shape(spark, sf)) == [(True,)]


@pytest.mark.parametrize("name", ["net_events_48h", "parallel_edges_noisy_or"])
def test_many_edges_are_found_without_a_shuffle(spark, sf, monkeypatch, name):
    """Where meetings are many an edge leaves its task once, and is the same."""
    from nudgegraph import catalogue

    want = rows_of(catalogue.QUERIES[name](spark, sf))
    monkeypatch.setattr(meetings, "LOCAL_EDGES", 0)
    monkeypatch.setattr(meetings, "MEETINGS_AT_ONCE", 100)
    got = catalogue.QUERIES[name](spark, sf)
    assert "Exchange" not in got._jdf.queryExecution().executedPlan().toString() and rows_of(got) == want


def test_parallel_edges_of_networks(spark, both):
    """The likeliest or any of two networks' edges, with sure ones; an actor who meets others in just one of them."""
    log = [(1, "a", 0), (2, "a", 60), (3, "a", 7_300), (1, "b", 0), (2, "b", 60), (4, "b", 9_000), (3, "c", 0), (5, "c", 60)]
    actions = spark.createDataFrame(log, "actor long, action string, s long").select("actor", "action", F.timestamp_seconds("s").alias("ts"))
    settings = [("1 hours", 3.0), ("3 hours", 0.5)]
    edges = [BoostGraph.from_edges(net.learn_probabilities(actions, None, *s)).edges for s in settings]
    for how in ("max", "noisy_or"):
        want, got = (sorted((r.src, r.dst, round(r.p, 9), round(r.q, 9)) for r in df.collect()) for df in (net.merge_parallel(edges[0].unionByName(edges[1]), how), net.merge_parallel(meetings.meeting_graphs(actions, settings), how)))
        assert got == want and len(got) == 6 and any(p == 1 for *_, p, _ in got)


@pytest.mark.parametrize("beta", [2.0, 4.0, 2.5])
def test_other_exponents(both, monkeypatch, beta):
    """Edges raised with another exponent are found from the actions too."""
    held, found = (g.raised(beta) for g in both)
    assert rows_of(sample_sketches(held, [100, 203], 0, 60, 3)) == rows_of(sample_sketches(found, [100, 203], 0, 60, 3))
    monkeypatch.setattr(meetings.MeetingGraph, "listed", lambda self: pytest.fail("edges are listed"))
    assert world_counts(found, [100, 203], [([104, 205, 211, 212], "receiver")], 30).agg(F.sum("n0")).first()[0] > 0
    monkeypatch.undo()
    close = lambda g: [tuple(round(x, 12) for x in r) for r in rows_of(g.edges)]
    assert close(held) == close(found)


@pytest.mark.parametrize("kept", [1 << 28, 0])
def test_worlds_are_found_once_for_all_sets(both, spark, monkeypatch, kept):
    """Gains come from what boosted nodes add to worlds without a boost; those are run once, or anew where they aren't kept."""
    monkeypatch.setattr(diffusion, "KEPT_WORLDS", kept)
    seeds, sets = [100, 5], [[104, 205, 211, 212, 230], [], list(range(100, 140)), list(range(200, 235))]
    arms = [(s, m) for s in sets for m in ("receiver", "sender", "single_boost")]
    for g in both:
        got = {r.world: tuple(r)[1:] for r in world_counts(g, seeds, arms, 25).collect()}
        plain = [{r.world: r.n for r in diffusion.world_spread(simulate(g, seeds, s, 25, mode=m)).collect()} for s, m in arms]
        assert got == {w: tuple(p[w] for p in plain) for w in range(25)}
        assert len(g.__dict__.get("_worlds", {})) == (1 if kept else 0)
        assert diffusion.boost_mc(g, seeds, sets[2], 25).first().delta >= 0 and len(g.__dict__.get("_worlds", {})) == (1 if kept else 0)


def test_exponents_list_no_edge(spark, sf, monkeypatch):
    from nudgegraph.workloads import experiments

    monkeypatch.setattr(meetings, "LOCAL_EDGES", 0)
    monkeypatch.setattr(meetings.MeetingGraph, "listed", lambda self: pytest.fail("edges are listed"))
    grid = experiments.replace(experiments.SMALL, nets=("events_6h",), ks=(5,), theta=200, runs=40)
    got = experiments.w08(spark, sf, grid).where("measure = 'boost'").collect()
    assert {r.beta for r in got} == {2.0, 4.0} and max(r.value for r in got) > 0


def test_boosted_nodes_add_what_they_reach(spark):
    """Gains on a graph of small chances, whose boosted nodes reach others that are boosted or not."""
    import random

    rng = random.Random(5)
    rows = [(u, v, 0.04, 0.5) for u in range(60) for v in rng.sample(range(60), 9) if u != v]
    g = BoostGraph.from_edges(spark.createDataFrame(rows, "src long, dst long, p double, q double"))
    boost, no = list(range(3, 30)), []
    got = {r.world: (r.n0, r.n1) for r in world_counts(g, [0, 1], [(boost, "receiver"), (no, "receiver")], 60).collect()}
    plain = [{r.world: r.n for r in diffusion.world_spread(simulate(g, [0, 1], s, 60)).collect()} for s in (boost, no)]
    assert got == {w: (plain[0][w], plain[1][w]) for w in range(60)} and sum(a > b + 5 for a, b in got.values()) > 10

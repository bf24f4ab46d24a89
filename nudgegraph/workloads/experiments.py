"""The experiment workloads on the given tables, as long tables of measures.

Every ``wNN(spark, sf_dir, grid)`` returns rows (exp, net, solver, seeds_mode,
k, beta, eps, rep, measure, value, stderr). ``grid_for`` has the parameters
for a scale; any entry can be replaced.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nudgegraph.model import BoostGraph, BoostProblem, Solution, with_boost
from nudgegraph.operators.baselines import hop_profile
from nudgegraph.operators.diffusion import boost_exact, boost_mc, spread_exact, spread_exact_of, spread_mc
from nudgegraph.operators.sketches import critical_shares, sandwich_scatter, sketch_stats
from nudgegraph.operators.trees import Tree, dp_rounded, greedy, spread
from nudgegraph.plans.planner import from_actions
from nudgegraph.plans.solvers import allocate_budget, seeds_influential, seeds_random, solve
from nudgegraph.session import Scratch
from nudgegraph.sources import networks as net
from nudgegraph.sources.tables import RUNS
from nudgegraph.workloads.networks import graph_stats, largest_wcc
from nudgegraph.workloads import sql
from nudgegraph.workloads.sampled import COVER, COVER_SHAPE, GATE, GATE_SHAPE, HAIR, PATH, PATH_SHAPE, STAR, STAR_SHAPE

SOLVERS = ("sketch_full", "sketch_critical")
BASELINES = ("degree_global", "degree_local", "influence_rank", "extra_seeds")


@dataclass(frozen=True)
class Grid:
    nets: tuple[str, ...] = ("customers", "events_6h", "suppliers", "embeddings")
    ks: tuple[int, ...] = (2, 10, 25, 50)
    betas: tuple[float, ...] = (2.0, 3.0, 4.0, 5.0, 6.0)
    runs: int = 1000
    seeds: int = 15
    random_sets: int = 5
    eps: float = 0.5
    theta: int | None = 6000
    sets: int = 300
    tree_n: int = 2000
    tree_eps: tuple[float, ...] = (0.2, 0.4, 0.6, 0.8, 1.0)
    tree_sizes: tuple[int, ...] = (250, 500, 1000, 2000)
    tree_k: int = 25
    tree_seeds: int = 50
    budget: int = 10
    ratios: tuple[int, ...] = (5, 10, 20, 40)
    fractions: tuple[float, ...] = (0.2, 0.4, 0.6, 0.8, 1.0)
    reps: int = 1
    salts: tuple[int, ...] = (1, 2, 3, 4, 5)


DEFAULT = Grid()
#: the general programme's step in w13
WIDE_STEP = 0.002


def grid_for(sf_dir: str) -> Grid:
    if sf_dir.rstrip("/").endswith("sf0.1"):
        return replace(DEFAULT, ks=(5, 50, 150, 500), seeds=50, runs=20_000, theta=None, budget=50, tree_k=50, reps=5)
    return DEFAULT


def network(spark: SparkSession, sf_dir: str, name: str, beta: float = 2.0) -> BoostGraph:
    if name == "events_6h" and beta == 2.0:
        graph = net.events_graph(spark, sf_dir)
        if from_actions(graph):
            return graph.largest()
        made = graph.edges.select("src", "dst", "p")
    else:
        made = {"customers": net.net_customers, "events_6h": net.net_events, "suppliers": net.net_suppliers, "embeddings": net.net_embeddings, "customers_90d": lambda s, d: net.net_customers(s, d, 90), "events_48h": lambda s, d: net.net_events(s, d, 48, 1.0)}[name](spark, sf_dir)
    scratch = Scratch(spark, "net")
    whole = scratch.keep(made.where("p > 0"), "whole")  # read for the components and again for the edges of one
    graph = BoostGraph(scratch.keep(BoostGraph.from_edges(largest_wcc(whole), beta).edges, name))
    scratch.drop(whole)
    return graph


def measures(graph: BoostGraph) -> DataFrame:
    """One row: nodes, edges, mean chance."""
    if not from_actions(graph):
        return graph_stats(graph.edges)
    row = graph.spark.createDataFrame([(graph.n, *graph.measures)], "n long, m long, avg_p double")
    return row.withColumn("avg_p", F.round("avg_p", 6))


def _row(exp, measure, value, *, net="-", solver="-", mode="-", k=0, beta=2.0, eps=0.5, rep=0, stderr=0.0):
    return exp, net, solver, mode, int(k), float(beta), float(eps), int(rep), measure, float(value), float(stderr or 0.0)


def _table(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, RUNS)


def _problem(graph: BoostGraph, seeds: list[int], k: int) -> BoostProblem:
    return BoostProblem(graph, graph.spark.createDataFrame([(s,) for s in seeds], "node long"), min(k, graph.n - len(seeds)))


def _seeds(graph: BoostGraph, grid: Grid, mode: str, set_no: int = 0) -> list[int]:
    return seeds_influential(graph, min(grid.seeds, graph.n // 10 or 1), theta=grid.theta) if mode == "influential" else seeds_random(graph, max(2, graph.n // 30), set_no)


def _solve(problem: BoostProblem, method: str, grid: Grid, salt: int = 1, **more) -> tuple[Solution, float]:
    start = time.time()
    options = more if method == "sketch_full" else {}
    options = options | ({"theta": grid.theta, "salt": salt} if method in (*SOLVERS, "sandwich", "extra_seeds") else {"runs": max(200, grid.runs // 5)} if method.startswith("degree") else {})
    got = solve(problem, method, **options)
    return got, time.time() - start


def w01(spark: SparkSession, sf_dir: str, grid: Grid = DEFAULT) -> DataFrame:
    """Networks after learning, dropping zeros and keeping the largest component: size, mean chance, spread of both kinds of seeds."""
    rows = []
    for name in grid.nets:
        g = network(spark, sf_dir, name)
        s = measures(g).first()
        rows += [_row("w01", m, s[m], net=name) for m in ("n", "m", "avg_p")]
        for mode in ("influential", "random"):
            seeds = _seeds(g, grid, mode)
            r = spread_mc(g, seeds, runs=grid.runs).first()
            rows.append(_row("w01", "spread", r.spread, net=name, mode=mode, k=len(seeds), stderr=r.stderr))
    return _table(spark, rows)


def w02(spark: SparkSession, sf_dir: str, grid: Grid = DEFAULT) -> DataFrame:
    """Spread of influential seeds."""
    rows = []
    for name in grid.nets:
        g = network(spark, sf_dir, name)
        s = _seeds(g, grid, "influential")
        r = spread_mc(g, s, runs=grid.runs).first()
        rows.append(_row("w02", "spread", r.spread, net=name, mode="influential", k=len(s), stderr=r.stderr))
    return _table(spark, rows)


def w03(spark: SparkSession, sf_dir: str, grid: Grid = DEFAULT) -> DataFrame:
    """Spread of random seeds, set by set."""
    rows = []
    for name in grid.nets:
        g = network(spark, sf_dir, name)
        for i in range(grid.random_sets):
            s = _seeds(g, grid, "random", i)
            r = spread_mc(g, s, runs=grid.runs).first()
            rows.append(_row("w03", "spread", r.spread, net=name, mode="random", k=len(s), rep=i, stderr=r.stderr))
    return _table(spark, rows)


def memory(graph: BoostGraph, got: Solution) -> tuple[int, int]:
    """(all, extra) bytes: the edges as sent to a worker and the sketches; the sketches alone."""
    extra = int(sketch_stats(got.sketches).first().estimated_bytes) if got.sketches is not None else 0
    return 2 * 24 * graph.m + 24 * graph.n + extra, extra


def compare(spark: SparkSession, sf_dir: str, exp: str, grid: Grid, modes: tuple[str, ...], methods: tuple[str, ...], **more) -> DataFrame:
    """Boost, seconds by phase, bytes and sketch measures of each method by k; with random seeds for each of the sets."""
    rows = []
    for name in grid.nets:
        g = network(spark, sf_dir, name)
        for mode in modes:
            for set_no in range(grid.random_sets if mode == "random" else 1):
                seeds = _seeds(g, grid, mode, set_no)
                for k in grid.ks:
                    p = _problem(g, seeds, k)
                    for method in methods:
                        for rep in range(grid.reps):
                            got, seconds = _solve(p, method, grid, 1 + rep, **more)
                            at = {"net": name, "solver": method, "mode": mode, "k": k, "rep": set_no * grid.reps + rep}
                            r = boost_mc(g, seeds, got.boost, grid.runs).first()
                            rows += [_row(exp, "boost", r.delta, stderr=r.stderr, **at), _row(exp, "seconds", seconds, **at)]
                            rows += [_row(exp, f"seconds_{phase}", x, **at) for phase, x in got.report.values.get("seconds", {}).items()]
                            if got.sketches is not None:
                                s, (whole, extra) = sketch_stats(got.sketches).first(), memory(g, got)
                                rows += [_row(exp, m, s[m], **at) for m in ("raw_edges", "compressed_edges", "compression", "estimated_bytes", "critical_nodes", "touched", "theta") if s[m] is not None]
                                rows += [_row(exp, "total_bytes", whole, **at), _row(exp, "extra_bytes", extra, **at)]
    return _table(spark, rows)


def mean_of_reps(t: DataFrame) -> DataFrame:
    """The mean over repetitions and seed sets of each cell; its standard error from their spread."""
    keys = ["exp", "net", "solver", "seeds_mode", "k", "beta", "eps", "measure"]
    return t.groupBy(*keys).agg(F.avg("value").alias("value"), F.coalesce(F.stddev_samp("value") / F.sqrt(F.count("*")), F.lit(0.0)).alias("stderr"))


def w04(spark, sf_dir, grid: Grid = DEFAULT):
    """Boost by k with influential seeds, solvers and all baselines."""
    return compare(spark, sf_dir, "w04", grid, ("influential",), (*SOLVERS, *BASELINES))


def w05(spark, sf_dir, grid: Grid = DEFAULT):
    """Seconds by k and the speed-up of keeping critical nodes alone."""
    t = Scratch(spark, "w05").keep(compare(spark, sf_dir, "w05", grid, ("influential",), SOLVERS).where("measure = 'seconds'"), "rows")
    full, fast = (t.where(F.col("solver") == s).select("net", "k", "rep", F.col("value").alias(s)) for s in SOLVERS)
    up = full.join(fast, ["net", "k", "rep"]).select(F.lit("w05").alias("exp"), "net", F.lit("-").alias("solver"), F.lit("influential").alias("seeds_mode"), "k", F.lit(2.0).alias("beta"), F.lit(0.5).alias("eps"), "rep", F.lit("speedup").alias("measure"), (F.col(SOLVERS[0]) / F.col(SOLVERS[1])).alias("value"), F.lit(0.0).alias("stderr"))
    return t.unionByName(up)


def w06(spark, sf_dir, grid: Grid = DEFAULT):
    """Edges before and after compression, their ratio, and bytes, at the smallest and the largest k; and all that without compression."""
    ends = replace(grid, ks=(min(grid.ks), max(grid.ks)))
    kept = compare(spark, sf_dir, "w06", ends, ("influential",), SOLVERS)
    raw = compare(spark, sf_dir, "w06", replace(ends, ks=ends.ks[:1]), ("influential",), SOLVERS[:1], squeeze=False).withColumn("solver", F.lit("sketch_full_uncompressed"))
    return kept.unionByName(raw).where("measure not like 'seconds_%'")


def w07(spark, sf_dir, grid: Grid = DEFAULT, mode: str = "influential", exp: str = "w07"):
    """Share of the boost that the lower bound explains over perturbed sets, and the shares of critical nodes."""
    rows = []
    for name in grid.nets:
        g = network(spark, sf_dir, name)
        seeds = _seeds(g, grid, mode)
        for k in grid.ks:
            p = _problem(g, seeds, k)
            got, _ = _solve(p, "sketch_full", grid)
            others = [r.node for r in p.candidates().collect()]
            at = {"net": name, "solver": "sketch_full", "mode": mode, "k": k}
            points = sandwich_scatter(got.sketches, got.boost, sorted(others), g.n, got.report.theta, grid.sets).collect()
            rows += [_row(exp, "point_ratio", r.ratio, **at | {"rep": r.set_id}) for r in points] + [_row(exp, "point_boost", r.delta, **at | {"rep": r.set_id}) for r in points]
            if points:
                rows.append(_row(exp, "least_ratio", min(r.ratio for r in points), **at))
            rows.append(_row(exp, "ratio", got.report.lower_ratio, **at))
            c = critical_shares(got.sketches, got.boost).first()
            rows += [_row(exp, m, c[m], **at) for m in ("with_critical", "critical_boosted", "critical_not_boosted")]
    return _table(spark, rows)


def w08(spark, sf_dir, grid: Grid = DEFAULT):
    """Boost, seconds and ratio by the raised chance's exponent, at the largest k."""
    rows, k = [], max(grid.ks)
    for name in grid.nets:
        # the exponent changes raised chances only: edges and seeds are found once
        base = network(spark, sf_dir, name)
        seeds = _seeds(base, grid, "influential")
        for beta in grid.betas:
            g = base.raised(beta)
            p = _problem(g, seeds, k)
            for method in SOLVERS:
                got, seconds = _solve(p, method, grid)
                at = {"net": name, "solver": method, "mode": "influential", "k": k, "beta": beta}
                r = boost_mc(g, seeds, got.boost, grid.runs).first()
                rows += [_row("w08", "boost", r.delta, stderr=r.stderr, **at), _row("w08", "seconds", seconds, **at)]
                if method == "sketch_full":
                    rows.append(_row("w08", "ratio", got.report.lower_ratio, **at))
    return _table(spark, rows)


def w09(spark, sf_dir, grid: Grid = DEFAULT):
    """The same comparisons and ratios with random seeds."""
    return compare(spark, sf_dir, "w09", grid, ("random",), (*SOLVERS, *BASELINES)).unionByName(w07(spark, sf_dir, grid, "random", "w09"))


def w10(spark, sf_dir, grid: Grid = DEFAULT):
    """Spread by how a budget is split between seeds and boosts, and the gain over seeds alone."""
    rows = []
    for name in grid.nets:
        g = network(spark, sf_dir, name)
        for ratio in grid.ratios:
            got = {r.fraction: r for r in allocate_budget(g, grid.budget, ratio, grid.fractions, grid.runs, theta=grid.theta).collect()}
            for f, r in got.items():
                at = {"net": name, "solver": f"ratio={ratio} seeds={f:g}", "k": r.n_boosts}
                rows.append(_row("w10", "spread", r.spread, stderr=r.stderr, **at))
                if 1.0 in got:
                    rows.append(_row("w10", "gain_over_seeds", r.spread / got[1.0].spread - 1, **at))
    return _table(spark, rows)


def _tree_of(spark, pairs: DataFrame, grid: Grid, salt: int) -> Tree:
    """A tree with drawn chances, and influential seeds from reach sets on it."""
    edges = Scratch(spark, "tree").keep(with_boost(net.trivalency(net.two_way(pairs), salt)).select("src", "dst", "p", "q"), "edges")
    graph = BoostGraph.from_edges(edges)
    seeds = seeds_influential(graph, grid.tree_seeds, salt=salt, theta=20_000 if grid.theta else None)
    return Tree([tuple(r) for r in edges.collect()], set(seeds), 0)


def _tree(spark, n: int, salt: int, grid: Grid) -> Tree:
    return _tree_of(spark, net.complete_binary_tree(spark, n), grid, salt)


def _tree_rows(exp, tree, k, eps_list, variant="binary", step=None, **at):
    start = time.time()
    value = greedy(tree, k)[1]
    rows = [_row(exp, "boost", value, solver="tree_greedy", k=k, eps=0, **at), _row(exp, "seconds", time.time() - start, solver="tree_greedy", k=k, eps=0, **at)]
    for eps in eps_list:
        start = time.time()
        chosen, rounded, _ = dp_rounded(tree, k, eps, variant, step)
        rows += [_row(exp, "seconds", time.time() - start, solver="tree_dp", k=k, eps=eps, **at), _row(exp, "boost", spread(tree, set(chosen)) - spread(tree), solver="tree_dp", k=k, eps=eps, **at), _row(exp, "rounded", rounded, solver="tree_dp", k=k, eps=eps, **at)]
    return rows


def w11(spark, sf_dir, grid: Grid = DEFAULT):
    """Greedy against the rounded programme by its eps, on binary trees of one size and several draws."""
    rows = []
    for salt in grid.salts:
        rows += _tree_rows("w11", _tree(spark, grid.tree_n, salt, grid), grid.tree_k, grid.tree_eps, net=f"binary_{grid.tree_n}", rep=salt)
    return _table(spark, rows)


def w12(spark, sf_dir, grid: Grid = DEFAULT):
    """The same by the tree's size at one eps, several draws each."""
    rows = []
    for n in grid.tree_sizes:
        for salt in grid.salts:
            rows += _tree_rows("w12", _tree(spark, n, salt, grid), grid.tree_k, (grid.eps,), net=f"binary_{n}", rep=salt)
    return _table(spark, rows)


def w13(spark, sf_dir, grid: Grid = DEFAULT):
    """Greedy against the general programme on the tree of geography, whose nodes have any number of children.

    The step is stated: the one that eps = 1 calls for is about four times
    smaller, which by the growth of its cells is about 80 times the work.
    """
    rows = []
    for salt in grid.salts:
        tree = _tree_of(spark, net.tree_geography(spark, sf_dir), grid, salt)
        rows += _tree_rows("w13", tree, grid.tree_k, (1.0,), "general", WIDE_STEP, net="geography", rep=salt)
    return _table(spark, rows)


def w14(spark, sf_dir, grid: Grid = DEFAULT):
    """Worked examples by enumeration of all worlds."""
    cases = [("path", PATH, {0}, {1}), ("star", STAR, {1, 3}, {0}), ("cover", COVER, {0}, {1, 3}), ("gate", GATE, {0}, {3})]
    rows = []
    for name, edges, seeds, boost in cases:
        rows += [_row("w14", "spread", spread_exact(edges, seeds, boost), net=name, k=len(boost)), _row("w14", "boost", boost_exact(edges, seeds, boost), net=name, k=len(boost))]
    return _table(spark, rows)


def w15(spark, sf_dir, grid: Grid = DEFAULT):
    """The best further seed isn't the best node to boost: on the path, and by hops on a network."""
    rows = []
    for v in (1, 2):
        rows += [_row("w15", "boost", boost_exact(PATH, {0}, {v}), net="path", solver=f"boost {v}", k=1), _row("w15", "spread", spread_exact(PATH, {0, v}), net="path", solver=f"seed {v}", k=1)]
    g = network(spark, sf_dir, grid.nets[-1])
    p = _problem(g, _seeds(g, grid, "influential"), max(grid.ks))
    for method in ("sketch_critical", "extra_seeds"):
        got, _ = _solve(p, method, grid)
        hops = hop_profile(p, got.boost).where("hop is not null").agg((F.sum(F.col("hop") * F.col("n")) / F.sum("n")).alias("h")).first().h
        rows.append(_row("w15", "mean_hop", hops or 0, net=grid.nets[-1], solver=method, k=max(grid.ks)))
    return _table(spark, rows)


def w16(spark, sf_dir, grid: Grid = DEFAULT):
    """Edges examined a sketch and seconds by network: what the cost follows."""
    rows = []
    for name in grid.nets:
        g = network(spark, sf_dir, name)
        got, seconds = _solve(_problem(g, _seeds(g, grid, "random"), min(grid.ks)), "sketch_critical", grid)
        rows += [_row("w16", "touched", got.report.touched, net=name), _row("w16", "seconds", seconds, net=name), _row("w16", "m", g.m, net=name), _row("w16", "n", g.n, net=name), _row("w16", "theta", got.report.theta, net=name)]
    return _table(spark, rows)


#: what the registered queries run: two of the four networks, fewer draws
SMALL = replace(DEFAULT, nets=("events_6h", "embeddings"), ks=(2, 10), runs=1000, seeds=5, theta=4000, betas=(2.0, 4.0), random_sets=2, salts=(1,), tree_eps=(0.2, 1.0), tree_sizes=(250, 1000), tree_k=20)


def _cells(df: DataFrame, measure: str) -> dict:
    """(net, solver, k, beta, eps) to (mean, standard error) over repetitions."""
    out: dict = {}
    for r in df.where(F.col("measure") == measure).collect():
        out.setdefault((r.net, r.solver, r.k, r.beta, r.eps), []).append((r.value, r.stderr))
    return {at: (sum(v for v, _ in got) / len(got), sum(e for _, e in got) / len(got)) for at, got in out.items()}


def _kept(df: DataFrame) -> DataFrame:
    return Scratch(df.sparkSession, "workload").keep(df, "rows")


def _slack(*cells) -> float:
    return 3 * sum(e for _, e in cells)


def _boost_vs_k(mode):
    """By network: no baseline is above the solvers, boosts grow with k, the critical-only solver comes close."""

    def query(spark, sf_dir):
        rows = []
        for name in SMALL.nets:
            t = _cells(compare(spark, sf_dir, "check", replace(SMALL, nets=(name,)), (mode,), (*SOLVERS, *BASELINES)), "boost")
            by = {(s, k): v for (_, s, k, *_), v in t.items()}
            first = all(by["sketch_full", k][0] >= by[b, k][0] - _slack(by["sketch_full", k], by[b, k]) for k in SMALL.ks for b in BASELINES)
            grows = all(by[s, SMALL.ks[0]][0] <= by[s, SMALL.ks[-1]][0] + _slack(by[s, SMALL.ks[0]], by[s, SMALL.ks[-1]]) for s in SOLVERS)
            close = all(by["sketch_critical", k][0] >= 0.8 * by["sketch_full", k][0] - _slack(by["sketch_full", k], by["sketch_critical", k]) for k in SMALL.ks)
            contrast = all(by["extra_seeds", k][0] <= by["sketch_full", k][0] for k in SMALL.ks)
            rows.append((name, first, grows, close, contrast))
        return spark.createDataFrame(rows, "net string, solvers_first boolean, grows_with_k boolean, critical_is_close boolean, extra_seeds_below boolean")

    return query


def _speed(spark, sf_dir):
    """Keeping critical nodes alone is faster, over both networks together."""
    t = _cells(_kept(w05(spark, sf_dir, replace(SMALL, ks=(10,), theta=20_000))), "seconds")
    total = {s: sum(v for (_, x, *_), (v, _) in t.items() if x == s) for s in SOLVERS}
    return spark.createDataFrame([(total["sketch_critical"] < total["sketch_full"],)], "critical_is_faster boolean")


def _beta(spark, sf_dir):
    """By network: the boost grows with the exponent."""
    rows = []
    for name in SMALL.nets:
        t = _kept(w08(spark, sf_dir, replace(SMALL, nets=(name,), ks=(10,))))
        b = {(s, beta): v for (_, s, _, beta, _), v in _cells(t, "boost").items()}
        grows = all(b[s, 2.0][0] <= b[s, 4.0][0] + _slack(b[s, 2.0], b[s, 4.0]) for s in SOLVERS)
        rows.append((name, grows))
    return spark.createDataFrame(rows, "net string, boost_grows_with_beta boolean")


def _compress(spark, sf_dir):
    """The number of sketches is the one that the sampling rule calls for."""
    t = _kept(w06(spark, sf_dir, replace(SMALL, nets=SMALL.nets[:1], theta=None)))
    ratio, raw, small, size = (_cells(t, m) for m in ("compression", "raw_edges", "compressed_edges", "estimated_bytes"))
    full = [at for at in ratio if at[1] == "sketch_full"]
    ok = all(abs(ratio[at][0] - raw[at][0] / small[at][0]) < 1e-6 and ratio[at][0] >= 1 for at in full)
    less = all(size[at[0], "sketch_critical", *at[2:]][0] <= size[at][0] for at in full)
    unsqueezed = all(size[at][0] <= size[at[0], "sketch_full_uncompressed", *at[2:]][0] for at in full if (at[0], "sketch_full_uncompressed", *at[2:]) in size)
    return spark.createDataFrame([(ok, less, unsqueezed)], "ratio_of_averages boolean, critical_is_smaller boolean, uncompressed_is_larger boolean")


def _budget(spark, sf_dir):
    """Some mix beats seeds alone where boosts are cheap, and the cheaper they are the more it gains."""
    grid = replace(SMALL, nets=("events_6h",), ratios=(5, 20))
    t = _cells(_kept(w10(spark, sf_dir, grid)), "gain_over_seeds")
    best = {ratio: max(v for (_, s, *_), (v, _) in t.items() if s.startswith(f"ratio={ratio} ")) for ratio in grid.ratios}
    return spark.createDataFrame([(len(t) == len(grid.ratios) * len(grid.fractions), best[20] > 0, best[20] >= best[5] - 0.05)], "all_mixes boolean, a_mix_beats_seeds boolean, gain_grows_with_ratio boolean")


def _tree_eps(spark, sf_dir):
    """Greedy and the programme agree, eps hardly moves the boost but the time, greedy is far faster."""
    t = _kept(w11(spark, sf_dir, SMALL))
    boost, seconds = ({(s, eps): v[0] for (_, s, _, _, eps), v in _cells(t, m).items()} for m in ("boost", "seconds"))
    near = all(boost["tree_greedy", 0.0] >= 0.98 * boost["tree_dp", eps] for eps in SMALL.tree_eps)
    flat = abs(boost["tree_dp", 0.2] - boost["tree_dp", 1.0]) <= 0.02 * boost["tree_dp", 0.2]
    return spark.createDataFrame([(near, flat, seconds["tree_dp", 1.0] < seconds["tree_dp", 0.2], 10 * seconds["tree_greedy", 0.0] < seconds["tree_dp", 1.0])], "greedy_near_programme boolean, boost_flat_in_eps boolean, larger_eps_is_faster boolean, greedy_far_faster boolean")


def _tree_size(spark, sf_dir):
    t = _kept(w12(spark, sf_dir, SMALL))
    boost, seconds = ({(name, s): v[0] for (name, s, *_), v in _cells(t, m).items()} for m in ("boost", "seconds"))
    names = [f"binary_{n}" for n in SMALL.tree_sizes]
    overlap = all(abs(boost[n, "tree_greedy"] - boost[n, "tree_dp"]) <= 0.02 * boost[n, "tree_dp"] for n in names)
    return spark.createDataFrame([(overlap, all(seconds[n, "tree_greedy"] < seconds[n, "tree_dp"] for n in names), seconds[names[0], "tree_dp"] < seconds[names[-1], "tree_dp"])], "boosts_overlap boolean, greedy_is_faster boolean, programme_slows_with_size boolean")


def _tree_general(spark, sf_dir):
    t = _kept(w13(spark, sf_dir, SMALL))
    boost, rounded = ({s: v[0] for (_, s, *_), v in _cells(t, m).items()} for m in ("boost", "rounded"))
    return spark.createDataFrame([(boost["tree_greedy"] >= 0.98 * boost["tree_dp"], rounded["tree_dp"] <= boost["tree_dp"] + 1e-9)], "greedy_near_programme boolean, rounding_only_lowers boolean")


def _ratio(spark, sf_dir):
    """By network: all points lie in (0, 1], and neither the returned set's ratio nor the least one rises with k.

    Where no sketch shows a boost, as when seeds activate all, a k has no points and its least ratio counts as 1.
    """
    rows = []
    for name in SMALL.nets:
        t = _kept(w07(spark, sf_dir, replace(SMALL, nets=(name,), ks=(2, 10, 25))))
        by, least, points = (_cells(t, m) for m in ("ratio", "least_ratio", "point_ratio"))
        own, low = ({at[2]: v[0] for at, v in c.items()} for c in (by, least))
        rows.append((name, all(0 < v <= 1 for v, _ in points.values()) and all(0 < v <= 1 for v in own.values()), own[25] <= own[2] + 0.05, low.get(25, 1.0) <= low.get(2, 1.0) + 0.1))
    return spark.createDataFrame(rows, "net string, in_range boolean, falls_with_k boolean, least_falls_with_k boolean")


def _seed_spread(spark, sf_dir):
    """By network: influential seeds spread further than random ones of the same number."""
    rows = []
    for name in SMALL.nets:
        g = network(spark, sf_dir, name)
        a, b = seeds_influential(g, 5, theta=4000), [seeds_random(g, 5, i) for i in range(3)]
        best, other = spread_mc(g, a, runs=1000).first(), [spread_mc(g, x, runs=1000).first() for x in b]
        rows.append((name, all(best.spread >= o.spread - 3 * (best.stderr + o.stderr) for o in other)))
    return spark.createDataFrame(rows, "net string, influential_spread_further boolean")


def _cost_shape(spark, sf_dir):
    """Edges examined a sketch follow how easily activation spreads, not the network's size alone."""
    t = _cells(_kept(w16(spark, sf_dir, replace(SMALL, nets=("customers", "events_6h", "suppliers"), theta=1000))), "touched")
    by = {name: v[0] for (name, *_), v in t.items()}
    return spark.createDataFrame([(by["suppliers"] > by["customers"] and by["suppliers"] > by["events_6h"],)], "dense_costs_most boolean")


def _preparation(spark, sf_dir):
    """Nodes, edges and mean chance of each network's largest component."""
    out = None
    for name in DEFAULT.nets:
        row = measures(network(spark, sf_dir, name)).withColumn("net", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out.withColumn("avg_p", F.round("avg_p", 5))


EXAMPLES = [("path", PATH_SHAPE, {0}, (1,), sql.path_spread), ("star", STAR_SHAPE, {1, 3}, (0,), sql.star_spread), ("cover", COVER_SHAPE, {0}, (1, 3), sql.cover_spread), ("gate", GATE_SHAPE, {0}, (3,), sql.gate_spread)]


def _examples(spark, sf_dir):
    """The four worked shapes with each year's shares of orders as chances."""
    out, graphs = None, _kept(net.order_shares(spark, sf_dir))
    for name, shape, seeds, boost, _ in EXAMPLES:
        got = spread_exact_of(graphs, shape, seeds, [boost])
        measures = F.explode(F.create_map(F.lit("spread"), F.col("spread"), F.lit("boost"), F.col("delta"))).alias("measure", "value")
        got = got.select("graph", F.lit(name).alias("net"), measures).withColumn("value", F.round(F.col("value") + HAIR, 6))
        out = got if out is None else out.unionByName(got)
    return out


def _examples_sql() -> str:
    rows = " union all ".join(
        f"select graph, '{name}' as net, 'spread' as measure, {spread(b)} as value from g union all select graph, '{name}', 'boost', {spread(b)} - ({spread(())}) from g" for name, _, _, b, spread in EXAMPLES
    )
    return f"with g as materialized ({sql.ORDER_SHARES}) select graph, net, measure, round(value + {HAIR}, 6) as value from ({rows})"


def _contrast(spark, sf_dir):
    return w15(spark, sf_dir, SMALL).where("net = 'path'").select("solver", "measure", F.round("value", 6).alias("value"))


QUERIES = {
    "exp_boost_vs_k_p": _boost_vs_k("influential"), "exp_random_seeds_p": _boost_vs_k("random"), "exp_speedup_p": _speed, "exp_beta_p": _beta, "exp_compression_p": _compress, "exp_budget_p": _budget, "exp_sandwich_ratio_p": _ratio,
    "exp_tree_eps_p": _tree_eps, "exp_tree_size_p": _tree_size, "exp_tree_general_p": _tree_general, "exp_seed_spread_p": _seed_spread, "exp_cost_shape_p": _cost_shape, "exp_preparation": _preparation,
    "exp_worked_examples": _examples, "exp_seed_contrast": _contrast,
}


def _true(*columns: str, nets: bool = False) -> str:
    """All stated behaviours hold, for each network if they are told by network."""
    holds = ", ".join(f"true as {c}" for c in columns)
    return " union all ".join(f"select '{name}' as net, {holds}" for name in SMALL.nets) if nets else f"select {holds}"


def _preparation_sql() -> str:
    """Each network, its largest weak component and that component's measures."""
    parts = {"customers": sql.customers(), "events_6h": sql.events(), "suppliers": sql.SUPPLIERS, "embeddings": sql.EMBEDDINGS}
    out = []
    for i, (name, text) in enumerate(parts.items()):
        out.append(f"""e{i} as materialized (select src, dst, p from ({text}) where p > 0), b{i} as materialized (select src as a, dst as b from e{i} union select dst, src from e{i}),
r{i} as (select a as x, a as o from b{i} union select b{i}.b, r{i}.o from r{i} join b{i} on b{i}.a = r{i}.x), l{i} as materialized (select x, min(o) as c from r{i} group by x),
t{i} as materialized (select c from l{i} group by c order by count(*) desc, c limit 1), k{i} as materialized (select * from e{i} where src in (select x from l{i} where c = (select c from t{i})))""")
    rows = [f"select '{name}' as net, (select count(*) from (select src from k{i} union select dst from k{i})) as n, count(*) as m, round(round(avg(p), 6), 5) as avg_p from k{i}" for i, name in enumerate(parts)]
    return f"with recursive {', '.join(out)} {' union all '.join(rows)}"


_WANT = _true("solvers_first", "grows_with_k", "critical_is_close", "extra_seeds_below", nets=True)
ORACLES = {
    "exp_boost_vs_k_p": _WANT, "exp_random_seeds_p": _WANT, "exp_speedup_p": _true("critical_is_faster"), "exp_beta_p": _true("boost_grows_with_beta", nets=True), "exp_compression_p": _true("ratio_of_averages", "critical_is_smaller", "uncompressed_is_larger"),
    "exp_budget_p": _true("all_mixes", "a_mix_beats_seeds", "gain_grows_with_ratio"), "exp_sandwich_ratio_p": _true("in_range", "falls_with_k", "least_falls_with_k", nets=True),
    "exp_tree_eps_p": _true("greedy_near_programme", "boost_flat_in_eps", "larger_eps_is_faster", "greedy_far_faster"), "exp_tree_size_p": _true("boosts_overlap", "greedy_is_faster", "programme_slows_with_size"),
    "exp_tree_general_p": _true("greedy_near_programme", "rounding_only_lowers"), "exp_seed_spread_p": _true("influential_spread_further", nets=True), "exp_cost_shape_p": _true("dense_costs_most"), "exp_preparation": _preparation_sql(),
    "exp_worked_examples": _examples_sql(),
    "exp_seed_contrast": "select solver, measure, value::double as value from (values ('boost 1', 'boost', 0.22), ('seed 1', 'spread', 2.1), ('boost 2', 'boost', 0.02), ('seed 2', 'spread', 2.2)) t(solver, measure, value)",
}

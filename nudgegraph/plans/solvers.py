"""Solvers on general graphs, the sandwich, budgets, and the single entry point."""

from __future__ import annotations

import math
import time
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nudgegraph.functions.coins import coin
from nudgegraph.model import BoostGraph, BoostProblem, RunReport, Solution
from nudgegraph.operators import baselines
from nudgegraph.operators.diffusion import boost_exact, boost_mc, spread_mc, world_counts
from nudgegraph.operators.sketches import critical_incidence, delta_hat, head_incidence, mu_hat, nu_hat, reach_sets, sample_sketches, select_marginal, sketch_stats
from nudgegraph.plans.stopping import cover_greedy, inflate_ell, run_doubling, run_martingale
from nudgegraph.plans.planner import id_frame
from nudgegraph.session import Scratch


def _sampled(problem: BoostProblem, keep: str, eps: float, ell: float, salt: int, coins: str, strategy: str, most: int | None, theta: int | None, squeeze: bool = True, fresh_final: bool = False):
    g, scratch = problem.graph, Scratch(problem.graph.spark, "solve")
    seeds = problem.seed_ids
    draw = lambda lo, hi: sample_sketches(g, seeds, lo, hi, problem.k, salt, coins, strategy, keep, squeeze)
    held = lambda df: scratch.keep(df, "sketches")
    if theta is not None:
        from nudgegraph.plans.stopping import Sampled

        return Sampled(held(draw(0, theta)), theta, float("nan"), False)
    return run_martingale(draw, critical_incidence, held, g.n, problem.k, eps, inflate_ell(ell, g.n), most, fresh_final)


def _report(problem, sampled, seconds, eps, ell, **more) -> RunReport:
    stats = sketch_stats(sampled.sketches).first().asDict()
    ratio = more.get("lower_ratio")
    values = stats | {"certified": sampled.certified, "lower_bound": sampled.lower, "seconds": seconds, "confidence": 1 - problem.graph.n**-ell, **more}
    if ratio is not None:
        values["guarantee"] = max(0.0, (1 - 1 / math.e - eps) * ratio)
    return RunReport(values)


def solve_sketch_full(problem: BoostProblem, eps: float = 0.5, ell: float = 1.0, salt: int = 1, coins: str = "fast", strategy: str = "auto", max_sketches: int | None = None, theta: int | None = None, use_upper: bool = False, squeeze: bool = True, fresh_final: bool = False) -> Solution:
    """Better of the cover by critical nodes and the direct greedy, on the same sketches.

    With ``use_upper`` a third set covers the upper bound. The report carries
    the share of the boost that the lower bound explains.
    """
    start, n = time.time(), problem.graph.n
    sampled = _sampled(problem, "edges", eps, ell, salt, coins, strategy, max_sketches, theta, squeeze, fresh_final)
    sampling = time.time() - start
    barred = set(problem.seed_ids)
    k = min(problem.k, max(0, n - len(barred)))
    sets = {
        "lower": [v for v, _ in cover_greedy(critical_incidence(sampled.sketches), k, barred)],
        "direct": [v for v, _ in select_marginal(sampled.sketches, k, problem.seed_ids)],
    }
    if use_upper:
        sets["upper"] = [v for v, _ in cover_greedy(head_incidence(sampled.sketches), k, barred)]
    values = {name: delta_hat(sampled.sketches, b, n, sampled.theta) for name, b in sets.items()}
    best = max(sets, key=lambda name: (values[name], name == "lower"))
    mu = mu_hat(sampled.sketches, sets[best], n, sampled.theta)
    more = {"chosen": best, "delta_hat": values[best], "mu_hat": mu, "lower_ratio": mu / values[best] if values[best] else 1.0}
    if use_upper:
        nu = nu_hat(sampled.sketches, sets["upper"], n, sampled.theta)
        more |= {"nu_hat": nu, "upper_ratio": values["upper"] / nu if nu else 1.0}
    seconds = {"sampling": sampling, "selection": time.time() - start - sampling}
    return Solution(sets[best], _report(problem, sampled, seconds, eps, ell, **more), sampled.sketches)


def solve_sandwich(problem: BoostProblem, **options) -> Solution:
    return solve_sketch_full(problem, use_upper=True, **options)


def solve_sketch_critical(problem: BoostProblem, eps: float = 0.5, ell: float = 1.0, salt: int = 1, coins: str = "fast", strategy: str = "auto", max_sketches: int | None = None, theta: int | None = None) -> Solution:
    """The cover by critical nodes, on sketches that keep nothing else."""
    start, n = time.time(), problem.graph.n
    sampled = _sampled(problem, "critical", eps, ell, salt, coins, strategy, max_sketches, theta)
    sampling = time.time() - start
    barred = set(problem.seed_ids)
    picks = cover_greedy(critical_incidence(sampled.sketches), min(problem.k, max(0, n - len(barred))), barred)
    seconds = {"sampling": sampling, "selection": time.time() - start - sampling}
    return Solution([v for v, _ in picks], _report(problem, sampled, seconds, eps, ell, mu_hat=n * sum(c for _, c in picks) / sampled.theta), sampled.sketches)


def solve_bruteforce(edges: list[tuple[int, int, float, float]], seeds: set[int], k: int) -> tuple[list[int], float]:
    """Best set of at most k nodes of a tiny graph, by enumeration."""
    nodes = sorted({x for e in edges for x in e[:2]} - seeds)
    best, value = [], 0.0
    for size in range(1, k + 1):
        for chosen in combinations(nodes, size):
            v = boost_exact(edges, seeds, set(chosen))
            if v > value + 1e-12:
                best, value = list(chosen), v
    return best, value


def solve_mc_greedy(problem: BoostProblem, runs: int = 1000, most_nodes: int = 50, **options) -> Solution:
    """Greedy by simulation, for tiny graphs: k times n simulations."""
    if problem.graph.n > most_nodes:
        raise ValueError("greedy by simulation is for tiny graphs")
    nodes = [r.node for r in problem.candidates().orderBy("node").collect()]
    chosen: list[int] = []
    for _ in range(min(problem.k, len(nodes))):
        value = {v: boost_mc(problem.graph, problem.seed_ids, [*chosen, v], runs, **options).first().delta for v in nodes if v not in chosen}
        chosen.append(max(value, key=lambda v: (value[v], -v)))
    return Solution(chosen, RunReport({}))


def seeds_influential(graph: BoostGraph, count: int, eps: float = 0.5, ell: float = 1.0, salt: int = 11, coins: str = "fast", strategy: str = "auto", max_sketches: int | None = None, theta: int | None = None, framework: str = "martingale") -> list[int]:
    """Seeds of large spread by greedy cover of reach sets; found once for each graph and setting and kept with the graph.

    The sampling rules answer for a set of ``count`` nodes: where fewer cover all their samples, the smallest other ids make
    up the number. With a given ``theta`` the picks end there.
    """
    held_seeds, key = graph.__dict__.setdefault("_seeds", {}), (count, eps, ell, salt, coins, strategy, max_sketches, theta, framework)
    if key not in held_seeds:
        held_seeds[key] = _seeds_influential(graph, *key)
    return list(held_seeds[key])


def _seeds_influential(graph: BoostGraph, count: int, eps: float, ell: float, salt: int, coins: str, strategy: str, max_sketches: int | None, theta: int | None, framework: str) -> list[int]:
    scratch = Scratch(graph.spark, "seeds")
    draw = lambda lo, hi: reach_sets(graph, lo, hi, salt, coins, strategy)
    held = lambda df: scratch.keep(df, "reach")
    if theta is not None:
        sets = held(draw(0, theta))
    else:
        rule = {"martingale": run_martingale, "doubling": run_doubling}[framework]
        sets = rule(draw, lambda df: df, held, graph.n, count, eps, ell, max_sketches).sketches
    picks = [v for v, _ in cover_greedy(sets, count, unique=True)]
    scratch.drop(*scratch.frames())
    if theta is None and len(picks) < count:
        rest = graph.nodes.join(id_frame(graph.spark, picks), "node", "left_anti").orderBy("node").limit(count - len(picks))
        picks += [r.node for r in rest.collect()]
    return picks


def seeds_random(graph: BoostGraph, count: int, set_no: int = 0, mode: str = "portable") -> list[int]:
    """A uniform set of nodes that the set's number gives."""
    rows = graph.nodes.select("node", coin(mode, 1000 + set_no, F.lit(0), "node").alias("h")).orderBy("h", "node").limit(count).collect()
    return sorted(r.node for r in rows)


def spread_reach(sets: DataFrame, seeds: list[int], n: int, theta: int) -> float:
    """Spread estimated by the share of reach sets that the seeds hit."""
    return n * sets.join(id_frame(sets.sparkSession, seeds), "node", "left_semi").select("sketch").distinct().count() / theta


def solve_extra_seeds(problem: BoostProblem, eps: float = 0.5, ell: float = 1.0, salt: int = 13, coins: str = "fast", strategy: str = "auto", max_sketches: int | None = None, theta: int | None = None) -> Solution:
    """Nodes that, as further seeds, would raise the spread most: a contrast to boosting.

    Reach sets know no seeds: they are drawn once for each graph and setting and kept with the graph.
    """
    g, scratch = problem.graph, Scratch(problem.graph.spark, "extra")
    seeds, drawn = problem.seed_ids, problem.graph.__dict__.setdefault("_reach", {})

    def draw(lo: int, hi: int) -> DataFrame:
        key = (lo, hi, salt, coins, strategy)
        if key not in drawn:
            drawn[key] = scratch.keep(reach_sets(g, *key), "reach")
        sets = drawn[key]
        return sets.join(sets.join(id_frame(g.spark, seeds), "node", "left_semi").select("sketch").distinct(), "sketch", "left_anti")

    held = lambda df: scratch.keep(df, "open")
    sets = held(draw(0, theta)) if theta is not None else run_martingale(draw, lambda df: df, held, g.n, problem.k, eps, ell, max_sketches).sketches
    return Solution([v for v, _ in cover_greedy(sets, problem.k, set(seeds))], RunReport({}))


def allocate_budget(graph: BoostGraph, total: int = 100, cost_ratio: int = 100, fractions: tuple[float, ...] = (0.2, 0.4, 0.6, 0.8, 1.0), runs: int = 20_000, method: str = "sketch_critical", salt: int = 1, **options) -> DataFrame:
    """(fraction, n_seeds, n_boosts, capped, spread, stderr): the budget split between seeds and boosts.

    A seed costs as much as ``cost_ratio`` boosts; boosts beyond the number of
    other nodes are capped. Fraction one is pure seeding.
    """
    rows, spark = [], graph.spark
    for f in fractions:
        n_seeds = max(1, round(total * f))
        want = round((total - n_seeds) * cost_ratio)
        seeds = seeds_influential(graph, n_seeds, salt=salt + 10)
        n_boosts = min(want, graph.n - len(seeds))
        boost = solve(BoostProblem(graph, spark.createDataFrame([(s,) for s in seeds], "node long"), n_boosts), method, **options).boost if n_boosts else []
        r = spread_mc(graph, seeds, boost, runs, salt=salt).first()
        rows.append((float(f), len(seeds), len(boost), n_boosts < want, float(r.spread), float(r.stderr or 0.0)))
    return spark.createDataFrame(rows, "fraction double, n_seeds int, n_boosts int, capped boolean, spread double, stderr double")


def solve(problem: BoostProblem, method: str = "sketch_full", **options) -> Solution:
    """Run a solver or baseline by its name.

    Solvers may pick fewer than k nodes where no more would help; with
    ``fill=True`` the smallest other ids make up the number.
    """
    if options.pop("fill", False):
        got = solve(problem, method, **options)
        want = problem.k - len(got.boost)
        if want > 0:
            rest = problem.candidates().join(id_frame(problem.graph.spark, got.boost), "node", "left_anti").orderBy("node").limit(want)
            got.boost += [r.node for r in rest.collect()]
        return got
    if method == "tree_greedy":
        from nudgegraph.operators.trees import solve_tree_greedy

        return solve_tree_greedy(problem, **options)
    if method == "tree_dp":
        from nudgegraph.operators.trees import solve_tree_dp

        return solve_tree_dp(problem, **options)
    own = {"sketch_full": solve_sketch_full, "sketch_critical": solve_sketch_critical, "sandwich": solve_sandwich, "extra_seeds": solve_extra_seeds}
    if method in own:
        return own[method](problem, **options)
    if method in ("degree_global", "degree_local"):
        pick = baselines.degree_global if method == "degree_global" else baselines.degree_local
        kinds = options.pop("kinds", (1, 2, 3, 4))
        runs = options.pop("runs", 2000)
        return best_of(problem, [Solution(pick(problem, kind), RunReport({"kind": kind})) for kind in kinds], runs, **options)
    if method == "influence_rank":
        return Solution(baselines.influence_rank_pick(problem, **options), RunReport({}))
    raise ValueError(method)


def best_of(problem: BoostProblem, solutions: list[Solution], runs: int = 20_000, **options) -> Solution:
    """The solution with the largest simulated boost; ties to the first. All are judged in one job, each set once."""
    mode, sets = options.pop("mode", "receiver"), sorted({tuple(sorted(s.boost)) for s in solutions})
    counts = world_counts(problem.graph, problem.seed_ids, [*[(list(b), mode) for b in sets], (None, "receiver")], runs, **options)
    means = counts.agg(*[F.avg(F.col(f"n{i}") - F.col(f"n{len(sets)}")).alias(f"delta{i}") for i in range(len(sets))]).first()
    by_set = dict(zip(sets, means, strict=True))
    values = [by_set[tuple(sorted(s.boost))] for s in solutions]
    return solutions[max(range(len(solutions)), key=lambda i: (values[i], -i))]


def evaluate(problem: BoostProblem, solution: Solution, runs: int = 20_000, **options) -> tuple[float, float]:
    """(simulated boost, its standard error)."""
    r = boost_mc(problem.graph, problem.seed_ids, solution.boost, runs, **options).first()
    return float(r.delta), float(r.stderr or 0.0)

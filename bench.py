"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def timed(f) -> float:
    start = time.time()
    f()
    return round(time.time() - start, 3)


def main() -> None:
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.driver.memory", "12g").config("spark.sql.shuffle.partitions", CPUS).config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from nudgegraph import catalogue
    from nudgegraph.operators.diffusion import boost_mc
    from nudgegraph.operators.sketches import sample_sketches, sketch_stats
    from nudgegraph.operators.trees import Tree, dp_rounded, greedy
    from nudgegraph.model import BoostProblem, with_boost
    from nudgegraph.plans.solvers import seeds_random, solve
    from nudgegraph.sources import networks as net
    from nudgegraph.workloads.experiments import network

    queries, extra = {}, {}
    noop = lambda df: df.write.format("noop").mode("overwrite").save()
    for name in ("net_customers", "net_suppliers", "net_events_6h", "forest_orders", "join_range", "window_frames", "agg_cube", "stream_tumbling"):
        queries[name] = timed(lambda name=name: noop(catalogue.QUERIES[name](spark, SF_DIR)))
    held = {}
    queries["prepare_customers"] = timed(lambda: held.setdefault("g", network(spark, SF_DIR, "customers")))
    g = held["g"]
    seeds = seeds_random(g, max(2, g.n // 30))
    problem = BoostProblem(g, spark.createDataFrame([(s,) for s in seeds], "node long"), 50)
    sketches = 100_000
    queries["sketches_full_100k"] = timed(lambda: held.setdefault("full", sketch_stats(sample_sketches(g, seeds, 0, sketches, 50)).first()))
    queries["sketches_critical_100k"] = timed(lambda: held.setdefault("critical", sketch_stats(sample_sketches(g, seeds, 0, sketches, 1, keep="critical")).first()))
    extra["sketches_per_second"] = round(sketches / queries["sketches_full_100k"])
    extra["edges_examined_per_second"] = round(held["full"].touched * sketches / queries["sketches_full_100k"])
    extra["compression"] = round(held["full"].compression, 2)
    extra["critical_speedup"] = round(queries["sketches_full_100k"] / queries["sketches_critical_100k"], 2)
    for method in ("sketch_critical", "sketch_full"):
        options = {"max_sketches": 100_000} if method == "sketch_critical" else {"theta": 50_000}
        small = problem if method == "sketch_critical" else BoostProblem(g, problem.seeds, 10)
        queries[f"solve_{method}"] = timed(lambda method=method, small=small, options=options: held.__setitem__(method, solve(small, method, **options)))
    queries["evaluate_20000_runs"] = timed(lambda: held.__setitem__("boost", boost_mc(g, seeds, held["sketch_critical"].boost, 20_000).first()))
    extra["boost"] = round(held["boost"].delta, 3)
    edges = [tuple(r) for r in with_boost(net.trivalency(net.two_way(net.complete_binary_tree(spark, 2000)))).select("src", "dst", "p", "q").collect()]
    tree = Tree(edges, set(range(0, 2000, 40)), 0)
    queries["tree_greedy_2000_k50"] = timed(lambda: greedy(tree, 50))
    queries["tree_dp_2000_k10"] = timed(lambda: held.__setitem__("dp", dp_rounded(tree, 10, 1.0, "binary")))
    queries["forest_greedy"] = timed(lambda: noop(catalogue.QUERIES["forest_greedy"](spark, SF_DIR)))
    print(json.dumps({"metric": "headline_total", "value": round(sum(queries.values()), 3), "unit": "sec", "queries": queries, "sf": os.path.basename(SF_DIR.rstrip("/")), **extra}))


if __name__ == "__main__":
    main()

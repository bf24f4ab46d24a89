"""Reach sets and boost sketches: sampling, compression and estimates.

Sketch i has a root and a world of its own, both pure functions of the salt
and i, so any range of sketches can be drawn anywhere and drawn again.
"""

from __future__ import annotations

from collections import Counter, defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nudgegraph.functions.coins import coin, root_array, root_coin, threshold
from nudgegraph.model import SKETCHES, SUPER, BoostGraph
from nudgegraph.operators.kernels import Workspace, activates, compress, grow, marginal_nodes, reach_set
from nudgegraph.plans.planner import choose, id_frame, positions, sent
from nudgegraph.session import Scratch


def _range(graph: BoostGraph, first: int, last: int) -> DataFrame:
    parts = max(1, min(last - first, 4 * graph.spark.sparkContext.defaultParallelism))
    return graph.spark.range(first, last, 1, parts).withColumnRenamed("id", "sketch")


def draw_roots(graph: BoostGraph, first: int, last: int, salt: int, coins: str = "fast") -> DataFrame:
    """(sketch, root): a uniform node for each sketch, by a join on its dense number."""
    drawn = _range(graph, first, last).withColumn("idx", root_coin(coins, salt, "sketch") % graph.n)
    return drawn.join(graph.nodes.withColumnRenamed("node", "root"), "idx").select("sketch", "root")


def reach_sets(graph: BoostGraph, first: int, last: int, salt: int = 1, coins: str = "fast", strategy: str = "auto") -> DataFrame:
    """(sketch, node): all nodes that would activate the sketch's root."""
    if choose(graph, strategy) == "local":
        held = sent(graph)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            g = held.value
            space = Workspace(len(g["nodes"]))
            for batch in batches:
                ids = batch.column(0).to_numpy()
                roots = root_array(coins, salt, ids) % len(g["nodes"])
                found, size = [], 0
                for i, root in zip(ids.tolist(), roots.tolist(), strict=True):
                    nodes = g["nodes"][reach_set(g, root, i, salt, coins, space)]
                    found.append((i, nodes))
                    size += len(nodes)
                    if size > 100_000 or i == ids[-1]:
                        yield pa.RecordBatch.from_arrays([pa.array(np.repeat([i for i, _ in found], [len(x) for _, x in found])), pa.array(np.concatenate([x for _, x in found]))], ["sketch", "node"])
                        found, size = [], 0

        return _range(graph, first, last).mapInArrow(run, "sketch long, node long")
    scratch = Scratch(graph.spark, "reach")
    edges = graph.edges.select("src", "dst", threshold("p").alias("tp"))
    front = scratch.keep(draw_roots(graph, first, last, salt, coins).withColumnRenamed("root", "node"), "front")
    seen = [front]
    while not front.isEmpty():
        met = front.select("sketch", F.col("node").alias("dst")).join(edges, "dst").where(coin(coins, salt, "sketch", "src", "dst") < F.col("tp"))
        front = scratch.keep(_new_rows(met.select("sketch", F.col("src").alias("node")).distinct(), seen), "front")
        seen = _appended(seen, front, scratch)
    return _whole(seen)


def _new_rows(rows: DataFrame, parts: list[DataFrame]) -> DataFrame:
    """Rows whose (sketch, node) is in none of the parts."""
    for part in parts:
        rows = rows.join(part.select("sketch", "node"), ["sketch", "node"], "left_anti")
    return rows


def _whole(parts: list[DataFrame]) -> DataFrame:
    whole = parts[0]
    for part in parts[1:]:
        whole = whole.unionByName(part)
    return whole


def _appended(parts: list[DataFrame], new: DataFrame, scratch: Scratch, most: int = 6) -> list[DataFrame]:
    """The parts and a new one; beyond ``most`` they become one table, so each row is written again but once in a while."""
    parts = [*parts, new]
    if len(parts) <= most:
        return parts
    whole = scratch.keep(_whole(parts), "settled")
    scratch.drop(*parts[:-1])  # the new one is still read as the front
    return [whole]


def sample_sketches(graph: BoostGraph, seeds: list[int], first: int, last: int, cap: int, salt: int = 1, coins: str = "fast", strategy: str = "auto", keep: str = "edges", squeeze: bool = True) -> DataFrame:
    """One row a sketch, by the ``SKETCHES`` schema.

    ``cap`` bounds how many boosts a way to the root may need; with
    ``keep="critical"`` it is one, and critical nodes alone are kept.
    ``squeeze=False`` keeps the raw edges with merged seeds only.
    """
    cap = 1 if keep == "critical" else cap
    if choose(graph, strategy) == "local":
        held = sent(graph)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            g = held.value
            space = Workspace(len(g["nodes"]))
            is_seed = np.zeros(len(g["nodes"]), bool)
            is_seed[positions(g["nodes"], seeds)] = True
            seed_at = set(np.flatnonzero(is_seed).tolist())
            name = g["nodes"].tolist()
            for batch in batches:
                ids = batch.column(0).to_numpy()
                roots = root_array(coins, salt, ids) % len(name)
                rows = []
                for i, root in zip(ids.tolist(), roots.tolist(), strict=True):
                    category, raw, touched, _ = grow(g, is_seed, root, i, salt, coins, cap, space)
                    rows.append(_row(i, root, category, raw, touched, seed_at, cap, name, keep, squeeze))
                yield _batch(rows)

        return _range(graph, first, last).mapInArrow(run, SKETCHES)
    return _grow_relational(graph, seeds, first, last, cap, salt, coins, keep, squeeze)


def _merged_only(root: int, raw, seeds: set[int], cap: int):
    """Raw edges with the seeds' live closure as one node, nothing else dropped."""
    ahead: dict[int, list[int]] = {}
    for u, v, live in raw:
        if live:
            ahead.setdefault(u, []).append(v)
    merged, now = set(seeds), list(seeds)
    while now:
        for w in ahead.get(now.pop(), ()):
            if w not in merged:
                merged.add(w)
                now.append(w)
    return sorted({(SUPER if u in merged else u, v, live) for u, v, live in raw if v not in merged})


def _row(sketch, root, category, raw, touched, seeds, cap, name, keep, squeeze):
    edges, critical = ([], [])
    if category == "boostable":
        edges, critical = compress(root, raw, seeds, cap)
        if not squeeze:
            edges = _merged_only(root, raw, seeds, cap)
    to = (lambda v: v if v == SUPER else name[v]) if name is not None else (lambda v: v)
    named = [] if keep == "critical" else sorted((to(u), to(v), live) for u, v, live in edges)
    return sketch, to(root), category, named, sorted(to(v) for v in critical), len(raw), len(edges), touched


def _batch(rows) -> pa.RecordBatch:
    c = list(zip(*rows, strict=True)) if rows else [()] * 8
    edge = pa.list_(pa.struct([("src", pa.int64()), ("dst", pa.int64()), ("live", pa.bool_())]))
    kinds = [pa.int64(), pa.int64(), pa.string(), edge, pa.list_(pa.int64()), pa.int64(), pa.int32(), pa.int64()]
    values = [*c[:3], [[{"src": u, "dst": v, "live": x} for u, v, x in es] for es in c[3]], *c[4:]]
    return pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(values, kinds, strict=True)], ["sketch", "root", "category", "edges", "critical", "n_raw_edges", "n_edges", "n_touched"])


def _grow_relational(graph, seeds, first, last, cap, salt, coins, keep, squeeze) -> DataFrame:
    """A whole batch of sketches moves one layer a job; edges stay where they are, fronts move."""
    spark, scratch = graph.spark, Scratch(graph.spark, "grow")
    seed_frame = id_frame(spark, seeds)
    marked = F.broadcast(seed_frame.withColumn("seed", F.lit(True)))
    edges = graph.edges.select("src", "dst", threshold("p").alias("tp"), threshold("q").alias("tq"))
    edges = edges.join(F.broadcast(seed_frame.select(F.col("node").alias("src"), F.lit(True).alias("from_seed"))), "src", "left")
    roots = scratch.keep(draw_roots(graph, first, last, salt, coins), "roots")
    at_seed = roots.join(F.broadcast(seed_frame), F.col("root") == F.col("node"), "left_semi")
    rest = roots.join(at_seed.select("sketch"), "sketch", "left_anti")
    settled = [scratch.keep(rest.select("sketch", F.col("root").alias("node"), F.lit(0).alias("dist"), F.lit(False).alias("seed")), "settled")]
    open_, raws, later, d = settled[0].select("sketch", "node"), [], [], 0
    activated = [at_seed.select("sketch")]
    touched: list[DataFrame] = []
    h = coin(coins, salt, "sketch", "src", "dst")

    def placed(reached: DataFrame) -> DataFrame:
        new = _new_rows(reached.distinct(), settled)
        return scratch.keep(new.join(marked, "node", "left").select("sketch", "node", F.lit(d).alias("dist"), F.coalesce("seed", F.lit(False)).alias("seed")), "new")

    while True:
        while not open_.isEmpty():
            met = open_.select("sketch", F.col("node").alias("dst")).join(edges, "dst").withColumn("h", h)
            met = scratch.keep(met.select("sketch", "src", "dst", (F.col("h") < F.col("tp")).alias("live"), (F.col("h") < F.col("tq")).alias("raised"), F.col("from_seed").isNotNull().alias("from_seed")), "met")
            if d == 0:  # a live edge from a seed ends a sketch there, in the order of head and tail
                ends = scratch.keep(met.where("live and from_seed").groupBy("sketch").agg(F.min(F.struct("dst", "src")).alias("end")), "ends")
                activated.append(ends.select("sketch"))
                touched.append(met.join(ends, "sketch").where(F.struct("dst", "src") <= F.col("end")).groupBy("sketch").agg(F.count("*").alias("n")))
                met = met.join(ends.select("sketch"), "sketch", "left_anti")
            touched.append(met.groupBy("sketch").agg(F.count("*").alias("n")))
            kept = met.where("live" if d + 1 > cap else "raised").select("sketch", "src", "dst", "live")
            raws.append(kept)
            if d + 1 <= cap:
                later.append(kept.where("not live").select("sketch", F.col("src").alias("node")))
            new = placed(kept.where("live").select("sketch", F.col("src").alias("node")))
            settled = _appended(settled, new, scratch)
            open_ = new.where("not seed").select("sketch", "node")
        if not later:
            break
        done = _whole(activated)
        reached = _whole(later)
        later, d = [], d + 1
        new = placed(reached.join(done, "sketch", "left_anti"))
        settled = _appended(settled, new, scratch)
        open_ = new.where("not seed").select("sketch", "node")
    done, found = _whole(activated).distinct(), scratch.keep(_whole(settled), "found")
    met_seed = found.where("seed").select("sketch").distinct().join(done, "sketch", "left_anti").withColumn("category", F.lit("boostable"))
    category = roots.join(met_seed.unionByName(done.withColumn("category", F.lit("activated"))), "sketch", "left").select("sketch", "root", F.coalesce("category", F.lit("hopeless")).alias("category"))
    # nodes of distance zero keep one live edge, to the root
    near = found.where("dist = 0").select("sketch", F.col("node").alias("src"))
    short = near.join(roots, "sketch").where("src <> root").select("sketch", "src", F.col("root").alias("dst"), F.lit(True).alias("live"))
    raw, touch = _whole(raws).join(near, ["sketch", "src"], "left_anti").select("sketch", "src", "dst", "live").unionByName(short), _whole(touched)
    touch = touch.groupBy("sketch").agg(F.sum("n").alias("n_touched"))
    nested = raw.groupBy("sketch").agg(F.collect_list(F.struct("src", "dst", "live")).alias("raw"))
    whole = category.join(nested, "sketch", "left").join(touch, "sketch", "left")
    seed_set = set(seeds)

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for sketch, root, category, raw, n in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                edges = [(e["src"], e["dst"], e["live"]) for e in raw or ()] if category == "boostable" else []
                rows.append(_row(sketch, root, category, edges, n or 0, seed_set, cap, None, keep, squeeze))
            yield _batch(rows)

    return whole.select("sketch", "root", "category", "raw", "n_touched").mapInArrow(finish, SKETCHES)


def critical_incidence(sketches: DataFrame) -> DataFrame:
    """(sketch, node) of critical nodes."""
    return sketches.select("sketch", F.explode("critical").alias("node"))


def head_incidence(sketches: DataFrame) -> DataFrame:
    """(sketch, node) of all heads that a boost can open: an upper bound's sets."""
    return sketches.where("category = 'boostable'").select("sketch", F.explode(F.expr("array_distinct(transform(filter(edges, e -> not e.live), e -> e.dst))")).alias("node"))


def _flag(sketches: DataFrame, boost: list[int]) -> DataFrame:
    """Adds ``hit``: does boosting the set activate the root?"""
    chosen = set(boost)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hit = [activates(r, [(e["src"], e["dst"], e["live"]) for e in es], chosen) for r, es in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(hit, pa.bool_()), batch.column(3)], ["sketch", "hit", "critical"])

    return sketches.where("category = 'boostable'").select("sketch", "root", "edges", "critical").mapInArrow(run, "sketch long, hit boolean, critical array<long>")


def delta_hat(sketches: DataFrame, boost: list[int], n: int, theta: int) -> float:
    """Estimated boost: n times the share of sketches that the set activates."""
    return n * _flag(sketches, boost).where("hit").count() / theta


def _meets(column: str, nodes: list[int]):
    return F.arrays_overlap(column, F.array(*[F.lit(x) for x in nodes]).cast("array<long>")) if nodes else F.lit(False)


def mu_hat(sketches: DataFrame, boost: list[int], n: int, theta: int) -> float:
    """Estimated lower bound: the share whose critical nodes meet the set."""
    return n * sketches.where(_meets("critical", boost)).count() / theta


def nu_hat(sketches: DataFrame, boost: list[int], n: int, theta: int) -> float:
    """Estimated upper bound: the share in which some head to be opened is in the set."""
    return n * head_incidence(sketches).join(id_frame(sketches.sparkSession, boost), "node", "left_semi").select("sketch").distinct().count() / theta


def marginal_counts(sketches: DataFrame, boost: list[int]) -> DataFrame:
    """(node, n): in how many sketches boosting the node besides the set newly activates the root."""
    chosen = set(boost)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = [v for r, es in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True) for v in marginal_nodes(r, [(e["src"], e["dst"], e["live"]) for e in es], chosen)]
            yield pa.RecordBatch.from_arrays([pa.array(out, pa.int64())], ["node"])

    return sketches.where("category = 'boostable'").select("root", "edges").mapInArrow(run, "node long").groupBy("node").agg(F.count("*").alias("n"))


#: edges of sketches that the driver may hold to pick from
LOCAL_SKETCH_EDGES = 500_000


def _select_local(able: DataFrame, k: int, barred: set[int]) -> list[tuple[int, int]]:
    """The same picks on the driver: after a pick only sketches with an edge that it opens are counted again."""
    t = able.select("root", "edges").toArrow()
    rows = [(r, [(e["src"], e["dst"], e["live"]) for e in es]) for r, es in zip(t.column(0).to_pylist(), t.column(1).to_pylist(), strict=True)]
    opened: dict[int, list[int]] = defaultdict(list)
    for i, (_, es) in enumerate(rows):
        for v in {v for _, v, live in es if not live}:
            opened[v].append(i)
    nodes, chosen, picks = [marginal_nodes(r, es, set()) for r, es in rows], set(), []
    count = Counter(v for found in nodes for v in found)
    while len(picks) < k:
        n, v = max(((n, -v) for v, n in count.items() if n and v not in barred), default=(0, 0))
        if not n:
            break
        picks.append((-v, n))
        chosen.add(-v)
        for i in opened[-v]:
            count.subtract(nodes[i])
            nodes[i] = marginal_nodes(*rows[i], chosen)
            count.update(nodes[i])
    return picks


def select_marginal(sketches: DataFrame, k: int, barred: list[int] = ()) -> list[tuple[int, int]]:
    """[(node, newly activated)]: the best node by a full recount a pick, ties to the smallest id.

    The gain isn't submodular, so counts may grow and nothing can be lazy. Up
    to LOCAL_SKETCH_EDGES edges the driver picks; what a pick doesn't touch
    keeps its count.
    """
    picks: list[tuple[int, int]] = []
    able = sketches.where("category = 'boostable'")
    if (able.agg(F.sum(F.size("edges") + 1)).first()[0] or 0) <= LOCAL_SKETCH_EDGES:
        return _select_local(able, k, set(barred))
    out = id_frame(sketches.sparkSession, barred)
    while len(picks) < k:
        counts = marginal_counts(sketches, [v for v, _ in picks])
        top = counts.join(out, "node", "left_anti").orderBy(F.desc("n"), "node").first()
        if top is None:
            break
        picks.append((top.node, top.n))
    return picks


def equivalence_faults(graph: BoostGraph, seeds: list[int], first: int, last: int, cap: int, sets: list[list[int]], salt: int = 1, coins: str = "fast") -> int:
    """In how many (sketch, set) pairs the compressed sketch differs from the raw one."""
    small = sample_sketches(graph, seeds, first, last, cap, salt, coins)
    raw = sample_sketches(graph, seeds, first, last, cap, salt, coins, squeeze=False)
    wrong = 0
    for chosen in sets:
        a, b = _flag(small, chosen).select("sketch", "hit"), _flag(raw, chosen).select("sketch", F.col("hit").alias("other"))
        wrong += a.join(b, "sketch").where("hit <> other").count()
    return wrong


def sketch_stats(sketches: DataFrame) -> DataFrame:
    """One row of measures: counts, shares, edges and critical nodes a boostable sketch, edges examined, bytes."""
    able = F.col("category") == "boostable"
    return sketches.agg(
        F.count("*").alias("theta"),
        F.avg((F.col("category") == "activated").cast("double")).alias("activated"), F.avg((F.col("category") == "hopeless").cast("double")).alias("hopeless"), F.avg(able.cast("double")).alias("boostable"),
        F.avg(F.when(able, F.col("n_raw_edges"))).alias("raw_edges"), F.avg(F.when(able, F.col("n_edges"))).alias("compressed_edges"),
        F.try_divide(F.sum(F.when(able, F.col("n_raw_edges"))), F.sum(F.when(able, F.col("n_edges")))).alias("compression"),
        F.avg(F.when(able, F.size("critical"))).alias("critical_nodes"), F.avg("n_touched").alias("touched"),
        F.coalesce(F.sum(F.when(able, 17 * F.size("edges") + 8 * F.size("critical") + 32)), F.lit(0)).alias("estimated_bytes"),
    )


def critical_shares(sketches: DataFrame, boost: list[int]) -> DataFrame:
    """Of sketches that the set activates: (n, with critical nodes, with one boosted, with some but none boosted)."""
    hit = _flag(sketches, boost).where("hit")
    any_ = F.size("critical") > 0
    met = _meets("critical", boost)
    return hit.agg(
        F.count("*").alias("n"), F.coalesce(F.avg(any_.cast("double")), F.lit(0.0)).alias("with_critical"),
        F.coalesce(F.avg(met.cast("double")), F.lit(0.0)).alias("critical_boosted"), F.coalesce(F.avg((any_ & ~met).cast("double")), F.lit(0.0)).alias("critical_not_boosted"),
    )


def sandwich_scatter(sketches: DataFrame, chosen: list[int], candidates: list[int], n: int, theta: int, sets: int = 300, salt: int = 5) -> DataFrame:
    """(set_id, mu, delta, ratio) of perturbed sets whose boost is at least half of the chosen set's.

    A random number of members is replaced by other candidates. The sets, a
    bounded number, go to the workers; one pass over the sketches counts all.
    """
    rng = np.random.default_rng(salt)
    others = [v for v in candidates if v not in set(chosen)]
    made = []
    for _ in range(sets):
        out = int(rng.integers(0, min(len(chosen), len(others)) + 1))
        kept = rng.permutation(chosen)[out:].tolist()
        made.append(set(kept) | set(rng.permutation(others)[:out].tolist()))
    made.append(set(chosen))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mu, delta = np.zeros(len(made), np.int64), np.zeros(len(made), np.int64)
        for batch in batches:
            for root, edges, critical in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                es, crit = [(e["src"], e["dst"], e["live"]) for e in edges], set(critical)
                for i, b in enumerate(made):
                    m = bool(crit & b)
                    mu[i] += m
                    delta[i] += m or activates(root, es, b)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(made))), pa.array(mu), pa.array(delta)], ["set_id", "mu", "delta"])

    summed = sketches.where("category = 'boostable'").select("root", "edges", "critical").mapInArrow(run, "set_id long, mu long, delta long").groupBy("set_id").agg(F.sum("mu").alias("mu"), F.sum("delta").alias("delta"))
    best = summed.where(F.col("set_id") == len(made) - 1).select(F.col("delta").alias("best"))
    shown = summed.where(F.col("set_id") < len(made) - 1).crossJoin(F.broadcast(best)).where("2 * delta >= best and delta > 0")
    return shown.select("set_id", (F.col("mu") * n / theta).alias("mu"), (F.col("delta") * n / theta).alias("delta"), (F.col("mu") / F.col("delta")).alias("ratio"))

"""Networks of actions as arrays of the actions, not of the edges.

Who repeats an action within a window meets who did it before, so edges grow
with the square of the actors while actions grow with them. Sorted by action
and time, the ones that a row meets are a stretch of rows: a worker that holds
the rows finds any node's edges from its stretches, and no edge is ever stored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from nudgegraph.model import BoostGraph
from nudgegraph.operators.kernels import chances, met, parts
from nudgegraph.plans.planner import LOCAL_EDGES, sent
from nudgegraph.session import Scratch

#: rows of actions that may be sent to every worker, some 24 bytes each
LOCAL_ACTIONS = 8_000_000
#: meetings that a task counts together where it lists all edges
MEETINGS_AT_ONCE = 262_144


def _arrays(spark: SparkSession, actions: DataFrame, window: str, scale: float) -> dict | None:
    """What kernels need of the actions, or None where stretches can't be told by one number a row."""
    order = F.row_number().over(Window.partitionBy("action").orderBy("ts"))
    late = F.col("ts") + F.expr(f"interval {window}")
    rows = actions.where("actor is not null").select(F.col("actor").cast("long").alias("actor"), "ts", late.alias("late"), F.col("action").isNull().alias("lost"), (order == 1).alias("first"))
    t = rows.toArrow()
    actor, first = (t.column(c).to_numpy() for c in ("actor", "first"))
    actors, who = np.unique(actor, return_inverse=True)
    done = np.bincount(who, minlength=len(actors))
    timed = ~t.column("lost").to_numpy() & t.column("ts").is_valid().to_numpy()
    who, group = who[timed].astype(np.int32), np.cumsum(first)[timed]
    ts, late = (t.column(c).cast(pa.timestamp("us", t.schema.field(c).type.tz)).cast(pa.int64()).filter(pa.array(timed)).to_numpy() for c in ("ts", "late"))
    del t, actor, first, timed
    if not len(ts):
        return None
    start, span = int(ts.min()), int(late.max()) - int(ts.min()) + 2
    if (int(group.max()) + 1) * span >= 1 << 63:
        return None
    key, until = group * span + (ts - start), group * span + (late - start)
    del ts, late, group
    if (np.diff(key) < 0).any() or (np.diff(until) < 0).any():
        return None
    out_lo, out_hi = np.searchsorted(key, key, "right").astype(np.int32), np.searchsorted(key, until, "right").astype(np.int32)
    in_lo, in_hi = np.searchsorted(until, key, "left").astype(np.int32), np.searchsorted(key, key, "left").astype(np.int32)
    del key, until
    meets = np.zeros(len(actors), bool)
    meets[who[(out_hi > out_lo) | (in_hi > in_lo)]] = True
    return _placed(actors, done, who, np.argsort(who, kind="stable"), (out_lo, out_hi, in_lo, in_hi), meets, scale)


def _placed(names: np.ndarray, done: np.ndarray, who: np.ndarray, order: np.ndarray, stretches: tuple, keep: np.ndarray, scale: float) -> dict:
    """The arrays over the kept nodes; ``order`` has the rows that ``stretches`` are read in, node by node."""
    place = np.append(np.where(keep, np.cumsum(keep) - 1, -1), -1).astype(np.int32)  # the last one stands for no node
    at = place[who]
    order = order[at[order] >= 0]
    out = {"nodes": names[keep], "done": done[keep], "place": at, "scale": scale, "row_ptr": np.searchsorted(at[order], np.arange(int(keep.sum()) + 1))}
    for way, lo, hi in (("out", *stretches[:2]), ("in", *stretches[2:])):
        lo, hi = lo[order], hi[order]
        size = np.concatenate([[0], np.cumsum(hi.astype(np.int64) - lo)])
        out |= {f"{way}_lo": lo, f"{way}_hi": hi, f"{way}_ptr": size[out["row_ptr"]]}
    return out | {"rows": order.astype(np.int32)}


def _least_labels(n: int, links, at_once: int = 1_000_000) -> np.ndarray:
    """The least node that each of 0..n-1 is connected with; ``links`` are pairs of arrays, looked at in pieces."""
    label = np.arange(n)
    for whole in links:
        for i in range(0, len(whole[0]), at_once):
            a, b = (x[i : i + at_once] for x in whole)
            while len(a):
                x, y = label[a], label[b]
                apart = x != y
                a, b, x, y = a[apart], b[apart], x[apart], y[apart]
                np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
                while (label != label[label]).any():
                    label = label[label]
    return label


class _Raised:
    """A graph's sent arrays with another exponent: nothing is sent again."""

    def __init__(self, held, beta: float):
        self.held, self.beta = held, beta

    @property
    def value(self) -> dict:
        return self.held.value | {"beta": self.beta}


class MeetingGraph(BoostGraph):
    """A graph whose edges are found from rows of actions when they are asked for."""

    def __init__(self, spark: SparkSession, arrays: dict):
        self.__dict__.update(_spark=spark, arrays=arrays)

    @property
    def spark(self) -> SparkSession:
        return self._spark

    def raised(self, beta: float) -> MeetingGraph:
        """The same network raised with another exponent; arrays, and worlds in which nothing is boosted, are shared."""
        other = MeetingGraph(self.spark, self.arrays | {"beta": float(beta)})
        other.__dict__ |= {"_sent": _Raised(sent(self), float(beta)), "_worlds": self.__dict__.setdefault("_worlds", {})}
        return other

    @property
    def n(self) -> int:
        return len(self.arrays["nodes"])

    @property
    def meetings(self) -> int:
        return int(self.arrays["out_ptr"][-1])

    def _tasks(self, run, schema: str) -> DataFrame:
        """``run`` on each of about equal shares of the meetings: it gets the arrays and the nodes' places."""
        held, shares = sent(self), max(1, min(self.n, 8 * self.spark.sparkContext.defaultParallelism))

        def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            g = held.value
            ends = np.searchsorted(g["out_ptr"], np.linspace(0, g["out_ptr"][-1], shares + 1)[1:-1].astype(np.int64))
            ends = [0, *ends.tolist(), len(g["nodes"])]
            for batch in batches:
                for i in batch.column(0).to_pylist():
                    yield from run(g, np.arange(ends[i], ends[i + 1]))

        return self.spark.range(0, shares, 1, shares).mapInArrow(task, schema)

    def listed(self) -> DataFrame:
        """All edges, found anew by whoever reads them."""

        def run(g, nodes):
            for rows in parts(nodes, g["out_ptr"], MEETINGS_AT_ONCE):
                to, owner, hits = met(g, "out", rows)
                p, q = chances(g, owner, hits)
                yield pa.RecordBatch.from_arrays([pa.array(g["nodes"][owner]), pa.array(g["nodes"][to]), pa.array(p), pa.array(q)], ["src", "dst", "p", "q"])

        return self._tasks(run, "src long, dst long, p double, q double")

    @cached_property
    def edges(self) -> DataFrame:
        """The edges as a written table, for operators that join them."""
        return Scratch(self.spark, "meetings").keep(self.listed(), "edges")

    @cached_property
    def nodes(self) -> DataFrame:
        held = sent(self)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                yield pa.RecordBatch.from_arrays([pa.array(held.value["nodes"][batch.column(0).to_numpy()]), batch.column(0)], ["node", "idx"])

        return self.spark.range(self.n).mapInArrow(run, "node long, idx long")

    @cached_property
    def measures(self) -> tuple[int, float]:
        """(edges, mean chance): every edge is found, none leaves its task."""

        def run(g, nodes):
            m, total = 0, []
            for rows in parts(nodes, g["out_ptr"], MEETINGS_AT_ONCE):
                _, owner, hits = met(g, "out", rows)
                m += len(owner)
                total.append(float(chances(g, owner, hits)[0].sum()))
            yield pa.RecordBatch.from_arrays([pa.array([m]), pa.array([math.fsum(total)])], ["m", "total"])

        rows = self._tasks(run, "m long, total double").collect()
        m = sum(r.m for r in rows)
        return m, math.fsum(r.total for r in rows) / m if m else float("nan")

    @cached_property
    def m(self) -> int:
        return self.measures[0]

    def largest(self) -> MeetingGraph:
        """The largest weakly connected component; ties to the smaller id."""
        g = self.arrays
        lo, hi = g["out_lo"], g["out_hi"]
        some = hi > lo
        # a row meets its stretch's first row, and neighbours within a stretch are met by one row
        inside = np.zeros(len(g["place"]) + 1, np.int32)
        np.add.at(inside, lo[some], 1)
        np.add.at(inside, hi[some] - 1, -1)
        next_ = np.flatnonzero(np.cumsum(inside) > 0)
        owner = np.repeat(np.arange(self.n, dtype=np.int32), np.diff(g["row_ptr"]))
        label = _least_labels(self.n, [(owner[some], g["place"][lo[some]]), (g["place"][next_], g["place"][next_ + 1])])
        keep = label == np.bincount(label).argmax()
        if keep.all():
            return self
        whole = {}
        for c in ("out_lo", "out_hi", "in_lo", "in_hi"):
            whole[c] = np.zeros(len(g["place"]), np.int32)
            whole[c][g["rows"]] = g[c]
        who = np.where(g["place"] < 0, self.n, g["place"])
        return MeetingGraph(self.spark, _placed(g["nodes"], g["done"], who, g["rows"], tuple(whole.values()), keep, g["scale"]))


def meeting_graphs(actions: DataFrame, windows: list[tuple[str, float]]) -> list[MeetingGraph] | None:
    """The networks of the same actions by (window, scale), or None where an edge table suits better: few meetings, or too many actions to send."""
    spark = actions.sparkSession
    scratch = Scratch(spark, "actions")
    held = scratch.keep(actions, "rows")
    found = []
    if held.count() <= LOCAL_ACTIONS:
        found = [_arrays(spark, held, window, float(scale)) for window, scale in windows]
    scratch.drop(held)
    if not found or any(x is None for x in found) or max(int(x["out_ptr"][-1]) for x in found) <= LOCAL_EDGES:
        return None
    return [MeetingGraph(spark, x) for x in found]


def _any_works(x: np.ndarray, first: np.ndarray) -> np.ndarray:
    """The chance that any event of a stretch happens, as ``relational.noisy_or``."""
    sure = np.maximum.reduceat(x, first) >= 1
    return np.where(sure, 1.0, 1 - np.exp(np.add.reduceat(np.log1p(-np.where(x < 1, x, 0.0)), first)))


MERGES = {"max": np.maximum.reduceat, "noisy_or": _any_works}


def merged(graphs: list[MeetingGraph], how: str) -> DataFrame:
    """(src, dst, p, q), one edge a pair over all graphs: a task finds all of a node's edges, so none is shuffled."""
    spark, join = graphs[0].spark, MERGES[how]
    nodes = np.unique(np.concatenate([g.arrays["nodes"] for g in graphs]))
    many = np.zeros(len(nodes) + 1, np.int64)  # meetings of the nodes before, over all graphs
    places, needed = [], ("nodes", "done", "place", "scale", "row_ptr", "out_lo", "out_hi")
    for g in graphs:
        at = np.full(len(nodes), -1, np.int32)
        at[np.searchsorted(nodes, g.arrays["nodes"])] = np.arange(g.n)
        many[1:][at >= 0] += np.diff(g.arrays["out_ptr"])
        places.append(at)
    many = np.cumsum(many)
    shares = max(1, min(len(nodes), 8 * spark.sparkContext.defaultParallelism))
    ends = [0, *np.searchsorted(many, np.linspace(0, many[-1], shares + 1)[1:-1].astype(np.int64)).tolist(), len(nodes)]
    held = spark.sparkContext.broadcast((nodes, many, places, [{c: g.arrays[c] for c in needed} for g in graphs]))

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        nodes, many, places, arrays = held.value
        own = [np.searchsorted(nodes, g["nodes"]) for g in arrays]
        for batch in batches:
            for i in batch.column(0).to_pylist():
                for rows in parts(np.arange(ends[i], ends[i + 1]), many, MEETINGS_AT_ONCE):
                    key, p, q = [], [], []
                    for g, at, name in zip(arrays, places, own, strict=True):
                        to, owner, hits = met(g, "out", at[rows][at[rows] >= 0])
                        key.append(name[owner] * len(nodes) + name[to])
                        both = chances(g, owner, hits)
                        p.append(both[0])
                        q.append(both[1])
                    key = np.concatenate(key)
                    if not len(key):
                        continue
                    order = np.argsort(key, kind="stable")
                    key = key[order]
                    first = np.flatnonzero(np.diff(key, prepend=-1))
                    src, dst = np.divmod(key[first], len(nodes))
                    p, q = (join(np.concatenate(x)[order], first) for x in (p, q))
                    yield pa.RecordBatch.from_arrays([pa.array(nodes[src]), pa.array(nodes[dst]), pa.array(p), pa.array(q)], ["src", "dst", "p", "q"])

    return spark.range(0, shares, 1, shares).mapInArrow(task, "src long, dst long, p double, q double")


def action_graph(actions: DataFrame, window: str, scale: float = 1.0) -> BoostGraph:
    """The network that ``learn_probabilities`` learns from all pairs, chances raised with exponent 2.

    While its meetings are few, or the actions too many to send, the edges are
    a written table; between the two a worker finds them from the actions.
    """
    from nudgegraph.sources.networks import learn_probabilities

    spark = actions.sparkSession
    scratch = Scratch(spark, "actions")
    held = scratch.keep(actions, "rows")
    if held.count() <= LOCAL_ACTIONS:
        arrays = _arrays(spark, held, window, float(scale))
        if arrays is not None and int(arrays["out_ptr"][-1]) > LOCAL_EDGES:
            scratch.drop(held)
            return MeetingGraph(spark, arrays)
    graph = BoostGraph(scratch.keep(BoostGraph.from_edges(learn_probabilities(held, None, window, scale)).edges, "edges"))
    scratch.drop(held)
    return graph

"""Approximate nearest neighbours by vantage-point trees, one for each shard.

Vectors of length one make the chord a metric that orders as the cosine does.
A search skips a subtree when ``factor`` times the least distance that the
triangle inequality allows there is more than the distance of the k-th best so
far; with factor one no nearest neighbour is lost.
"""

from __future__ import annotations

import io
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from nudgegraph.llm.text import need
from nudgegraph.session import Scratch

# rounding of a cosine: 1e-12 there is 1e-6 of a chord near zero
_TIE, _SLACK = 1e-12, 2e-6


def build(vectors: np.ndarray, leaf: int = 128) -> dict[str, np.ndarray]:
    """Tree over rows of unit length, flat: rows in leaf order, and nodes.

    A node is (first row, end row, left, right, least and largest distance of
    the left and of the right rows); its vantage point is its first row, and
    left is -1 for a leaf.
    """
    order = np.arange(len(vectors))
    nodes: list[list[float]] = []
    todo = [(0, len(vectors), -1, 0)]
    while todo:
        lo, hi, parent, side = todo.pop()
        me = len(nodes)
        nodes.append([lo, hi, -1, -1, 0, 0, 0, 0])
        if parent >= 0:
            nodes[parent][2 + side] = me
        if hi - lo <= leaf:
            continue
        rows = order[lo:hi]
        # the point farthest from the first one stands at an edge and splits well
        far = lo + int(np.argmin(vectors[rows] @ vectors[rows[0]]))
        order[lo], order[far] = order[far], order[lo]
        rest = order[lo + 1 : hi].copy()
        d = np.sqrt(np.maximum(0, 2 - 2 * (vectors[rest] @ vectors[order[lo]])))
        half = len(rest) // 2
        by = np.argsort(d, kind="stable")
        if d[by[0]] == d[by[-1]]:  # all alike: nothing to split
            continue
        order[lo + 1 : hi], d = rest[by], d[by]
        nodes[me][4:] = [d[0], d[half - 1], d[half], d[-1]]
        todo += [(lo + 1, lo + 1 + half, me, 0), (lo + 1 + half, hi, me, 1)]
    return {"order": order, "nodes": np.array(nodes, float).reshape(-1, 8)}


class Search:
    """The k nearest of many queries in one tree, visited together.

    Rows are ranked by their squared chord, then by id; ``code`` numbers them
    in the order of ids.
    """

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, nodes: np.ndarray, k: int, factor: float):
        self.ids, self.vectors, self.nodes, self.k, self.factor = ids, vectors, nodes, k, factor
        self.by_id = np.argsort(ids, kind="stable")
        self.code = np.empty(len(ids), np.int64)
        self.code[self.by_id] = np.arange(len(ids))

    def run(self, qids: np.ndarray, queries: np.ndarray) -> np.ndarray:
        """For each query the rows found, nearest first; -1 where there are fewer."""
        n = len(qids)
        self.best = np.full((n, self.k), np.inf)
        self.best_code = np.full((n, self.k), len(self.ids))
        self.qids, self.queries = qids, queries
        if len(self.nodes) and n:
            self._visit(0, np.arange(n))
        return np.append(self.by_id, -1)[self.best_code]

    def _offer(self, q: np.ndarray, lo: int, hi: int) -> np.ndarray:
        """Takes rows lo..hi into account; chords to them."""
        square = np.maximum(0, 2 - 2 * (self.queries[q] @ self.vectors[lo:hi].T))
        own = np.where(self.ids[lo:hi][None, :] == self.qids[q][:, None], np.inf, square)
        code = np.where(np.isinf(own), len(self.ids), np.broadcast_to(self.code[lo:hi], own.shape))
        near, code = np.concatenate([self.best[q], own], 1), np.concatenate([self.best_code[q], code], 1)
        if near.shape[1] > 4 * self.k:
            # all rows as near as the k-th are ranked, so that ties go to small ids
            border = np.partition(near, self.k - 1, 1)[:, self.k - 1] + _TIE
            wide = int((near <= border[:, None]).sum(1).max())
            if wide < near.shape[1]:
                part = np.argpartition(near, wide - 1, 1)[:, :wide]
                near, code = np.take_along_axis(near, part, 1), np.take_along_axis(code, part, 1)
        rank = np.lexsort((code, np.round(near, 12)))[:, : self.k]
        self.best[q], self.best_code[q] = np.take_along_axis(near, rank, 1), np.take_along_axis(code, rank, 1)
        return np.sqrt(square)

    def _visit(self, node: int, q: np.ndarray) -> None:
        lo, hi, left, right, l0, l1, r0, r1 = self.nodes[node]
        if left < 0:
            for start in range(int(lo), int(hi), 4096):
                self._offer(q, start, min(start + 4096, int(hi)))
            return
        d = self._offer(q, int(lo), int(lo) + 1)[:, 0]
        near = d <= (l1 + r0) / 2
        bounds = {0: np.maximum(0, np.maximum(l0 - d, d - l1)), 1: np.maximum(0, np.maximum(r0 - d, d - r1))}
        for first, group in ((0, near), (1, ~near)):
            for side in (first, 1 - first):
                at = np.flatnonzero(group)
                open_ = bounds[side][at] * self.factor <= np.sqrt(self.best[q[at], -1]) + _SLACK
                if open_.any():
                    self._visit(int((left, right)[side]), q[at[open_]])


def _index(leaf: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}
        for batch in batches:
            for shard, vec_id, vector in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                held.setdefault(shard, []).append((vec_id, np.array(vector, float)))
        for shard, rows in held.items():
            by_size: dict[int, list] = {}
            for vec_id, v in rows:
                by_size.setdefault(len(v), []).append((vec_id, v))
            for some in by_size.values():
                ids, raw = np.array([r[0] for r in some], np.int64), np.stack([r[1] for r in some])
                unit = raw / np.sqrt((raw * raw).sum(1))[:, None]
                tree = build(unit, leaf)
                buffer = io.BytesIO()
                np.savez(buffer, ids=ids[tree["order"]], raw=raw[tree["order"]], nodes=tree["nodes"])
                yield pa.RecordBatch.from_arrays([pa.array([shard], pa.int32()), pa.array([buffer.getvalue()], pa.binary())], ["shard", "tree"])

    return run


def _usable(vectors: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    own = need(vectors, id_col, vector_col).toDF("vec_id", "v").where("vec_id is not null and v is not null and size(v) > 0")
    own = own.select("vec_id", F.expr("transform(v, x -> cast(x as double))").alias("v"))
    # by the largest component, a power of two: no square overflows or vanishes, and no digit changes
    whole = "forall(v, x -> x is not null and not isnan(x) and abs(x) < double('infinity')) and exists(v, x -> x <> 0)"
    own = own.where(whole).withColumn("top", F.expr("array_max(transform(v, x -> abs(x)))"))
    scale = F.pow(F.lit(2.0), F.greatest(F.lit(-1000), F.least(F.lit(1000), -F.floor(F.log2("top")))))
    return own.withColumn("by", scale).select("vec_id", F.expr("transform(v, x -> x * by)").alias("v"))


def cosine_neighbours(vectors: DataFrame, queries: DataFrame, *, id_col: str = "vec_id", vector_col: str = "embedding", k: int = 5, factor: float = 1.0, shard_rows: int = 8192, block: int = 4096, leaf: int = 128) -> DataFrame:
    """(query_id, rank, vec_id, score): for each query its k nearest others by cosine.

    ``queries`` has rows of ``vectors``; a query's own id is no candidate.
    Ties go to the smaller id; fewer than k candidates are all returned.
    Vectors that are null, empty, zero, or hold nulls, NaNs or infinities take
    no part, nor do null ids; vectors of other lengths than the query's are no
    candidates. Rows that repeat an id are candidates each. All rows are
    indexed; queries go to the trees in blocks of ``block``, hashed by id.
    """
    scratch = Scratch(vectors.sparkSession, "neighbours")
    own, asked = _usable(vectors, id_col, vector_col), _usable(queries, id_col, vector_col)
    n, n_queries = own.count(), asked.count()
    schema = "query_id long, vec_id long, score double"
    shards = max(1, -(-n // shard_rows))
    placed = own.withColumn("shard", F.pmod(F.xxhash64("vec_id"), F.lit(shards)).cast("int")).select("shard", "vec_id", "v")
    trees = scratch.keep(placed.repartition(shards, "shard").mapInArrow(_index(leaf), "shard int, tree binary"), "trees")
    blocks = max(1, -(-n_queries // block))
    found = None
    for b in range(blocks):
        some = asked.where(F.pmod(F.xxhash64("vec_id", F.lit(7)), F.lit(blocks)) == b).collect()
        by_size: dict[int, tuple[list, list]] = {}
        for r in some:
            ids, rows = by_size.setdefault(len(r.v), ([], []))
            ids.append(r.vec_id)
            rows.append(r.v)
        ready = {size: (np.array(ids, np.int64), np.array(rows, float)) for size, (ids, rows) in by_size.items()}
        sent = vectors.sparkSession.sparkContext.broadcast(ready)

        def run(batches: Iterator[pa.RecordBatch], sent=sent, k=k, factor=factor) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for blob in batch.column(1):
                    t = np.load(io.BytesIO(blob.as_py()))
                    ids, raw, nodes = t["ids"], t["raw"], t["nodes"]
                    if raw.shape[1] not in sent.value:
                        continue
                    qids, q = sent.value[raw.shape[1]]
                    length, q_length = (np.sqrt(np.cumsum(x * x, 1)[:, -1]) for x in (raw, q))
                    best = Search(ids, raw / length[:, None], nodes, k, factor).run(qids, q / q_length[:, None])
                    for lo in range(0, len(qids), 512):
                        row, col = np.nonzero(best[lo : lo + 512] >= 0)
                        i = best[lo : lo + 512][row, col]
                        # component by component in order: the same sum whoever computes it
                        dot = np.zeros(len(i))
                        for j in range(raw.shape[1]):
                            dot += q[lo + row, j] * raw[i, j]
                        yield pa.RecordBatch.from_arrays([pa.array(qids[lo + row]), pa.array(ids[i]), pa.array(dot / (length[i] * q_length[lo + row]))], ["query_id", "vec_id", "score"])

        part = scratch.keep(trees.mapInArrow(run, schema), "found")
        sent.destroy()
        found = part if found is None else found.unionByName(part)
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    ranked = found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    return ranked.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


ORACLE = """
with v as (
  select vec_id, list_transform(embedding, lambda x: x::double) as e from embeddings
  where vec_id is not null and embedding is not null and len(embedding) > 0
    and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0 and len(list_filter(embedding, lambda x: x <> 0)) > 0
), n as (
  select vec_id, e, sqrt(list_reduce(list_transform(e, lambda x: x * x), lambda a, b: a + b)) as l from v
), pairs as (
  select q.vec_id as query_id, c.vec_id,
         list_reduce(list_transform(list_zip(q.e, c.e), lambda z: z[1] * z[2]), lambda a, b: a + b) / (c.l * q.l) as score
  from n q join n c on q.vec_id <> c.vec_id and len(q.e) = len(c.e)
  where q.vec_id % 50 = 0
)
select query_id, rank::integer as rank, vec_id, score
from (select *, row_number() over (partition by query_id order by score desc, vec_id) as rank from pairs)
where rank <= 5
"""

"""Language model scoring by logistic mixing of hashed-context bit predictors.

A text is the sequence of its words (A-Z lower-cased, between ASCII white
space), written with one blank after each word but the last, and an end byte.
Every bit is predicted by several contexts, the last 1 to ``ORDERS`` bytes, each
with counts in a table that hashes of the context and of the bits so far
address; it has ``ROOM`` slots for each distinct node (context and bits so far)
of the training part, so that it is no fuller for a large corpus. Workers read
it from the shared folder; it doesn't pass through the driver. The predictions are mixed in the logistic domain with weights
that a gate chooses by bit position and by how much the longest contexts have
seen; an adaptive map from mixed to observed probability refines the result.
The product over all bits is the probability of the sequence.

Learning gathers byte sequences of the whole training part with their counts,
a table that grows with the corpus, and works on that: predictor counts are
sums over it, weights are learned online over it with each sequence's own
count left out, and the refinement is counted over it. Weights take their steps
shard by shard and are averaged; the shards are cut by a hash, as many as the
sequences call for, and read in the order of another, so the model is a function
of the texts alone, however they lie in partitions. A worker holds the table and
a batch of sequences at a time.
"""

from __future__ import annotations

import math
import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.parquet as pq
from pyarrow import fs
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nudgegraph.llm.text import need, trimmed, words_of
from nudgegraph.llm.warc import _store
from nudgegraph.session import Scratch, delete_path

ORDERS, STEPS = 5, 24
#: slots for each distinct node, and the least number of slots
ROOM, LEAST_SLOTS = 2, 1 << 12
#: sequences of one shard, and of one step of the weights
SHARD, STEP = 1 << 17, 1024
END = b"\n"
_C1, _C2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)
# longest context's and next one's counts, each in classes with these borders
_SEEN4, _SEEN3 = np.array([1, 4, 32]), np.array([1, 16])
GATES = 8 * (len(_SEEN4) + 1) * (len(_SEEN3) + 1)


def stream(words: list[bytes]) -> bytes:
    return b" ".join(words) + END


def _padded(streams: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Every byte with the ORDERS bytes before it, streams apart by ORDERS end bytes; and the streams' bounds.

    What lies between the bounds of two streams belongs to neither.
    """
    pad = END * ORDERS
    a = np.frombuffer(b"".join([pad + s for s in streams]), np.uint8)
    code = np.zeros(len(a) - ORDERS, np.int64)
    for j in range(ORDERS + 1):
        code <<= 8
        code |= a[j : len(a) - ORDERS + j]
    size = np.array([len(s) for s in streams], np.int64)
    start = np.cumsum(size + ORDERS) - size - ORDERS
    return code, np.stack([start, start + size], 1)


def grams(streams: list[bytes]) -> np.ndarray:
    """Every byte with the ORDERS bytes before it; end bytes stand before a stream."""
    code, bounds = _padded(streams)
    keep = np.ones(len(code), bool)
    for i in range(len(bounds) - 1):
        keep[bounds[i, 1] : bounds[i + 1, 0]] = False
    return code[keep]


def held_out(doc_id: int | None) -> bool:
    return doc_id is not None and zlib.crc32(str(doc_id).encode()) % 10 == 0


def slot_of(node: np.ndarray, size: int) -> np.ndarray:
    """The slot of each node's hash: its upper 31 bits as a share of ``size``, which is under 2^31."""
    return (((node >> np.uint64(33)) * np.uint64(size)) >> np.uint64(31)).view(np.int64)


class BitMixer:
    """Predictor counts, gated weights and refinement, as they are learned over arrays of byte sequences."""

    def __init__(self, n0: np.ndarray | None, n1: np.ndarray | None, weights: np.ndarray | None = None, refine: np.ndarray | None = None):
        self.n0, self.n1 = n0, n1
        self.weights = np.full((GATES, ORDERS + 1), 0.3) if weights is None else weights
        self.refine = refine

    @staticmethod
    def contexts(code: np.ndarray) -> list[np.ndarray]:
        """For each order the hash of its context."""
        with np.errstate(over="ignore"):
            return [(((code >> 8) & ((1 << (8 * o)) - 1)).astype(np.uint64) * np.uint64(8) + np.uint64(o)) * _C1 for o in range(1, ORDERS + 1)]

    @staticmethod
    def nodes(contexts: list[np.ndarray], code: np.ndarray, bit: int) -> list[np.ndarray]:
        """For each order the hash of the bit's (7 is the first) context and of the bits before it."""
        prefix = ((1 << (7 - bit)) | ((code & 255) >> (bit + 1))).astype(np.uint64)
        with np.errstate(over="ignore"):
            turn = prefix * _C2
            return [(h ^ turn) * _C2 for h in contexts]

    @staticmethod
    def slots(contexts: list[np.ndarray], code: np.ndarray, bit: int, size: int) -> list[np.ndarray]:
        """For each order the slot of the bit's node in a table of ``size`` slots."""
        return [slot_of(h, size) for h in BitMixer.nodes(contexts, code, bit)]

    def inputs(self, code: np.ndarray, bit: int, leave_out: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(stretched predictions with a bias, gate, the bit itself) of one bit of all sequences."""
        y = ((code >> bit) & 1).astype(bool)
        at = np.stack(self.slots(self.contexts(code), code, bit, len(self.n0)))
        n0, n1 = self.n0[at].astype(float), self.n1[at].astype(float)
        if leave_out:
            n1 = np.maximum(0, n1 - y)
            n0 = np.maximum(0, n0 - ~y)
        x = np.empty((len(code), ORDERS + 1))
        x[:, :ORDERS] = np.log((n1 + 0.05) / (n0 + 0.05)).T
        x[:, ORDERS] = 0.3
        seen = n0 + n1
        gate = (np.searchsorted(_SEEN4, seen[-1], "right") * (len(_SEEN3) + 1) + np.searchsorted(_SEEN3, seen[-2], "right")) * 8 + bit
        return x, gate, y

    @staticmethod
    def bucket(mixed: np.ndarray) -> np.ndarray:
        return np.clip(np.rint((np.clip(mixed, -8, 8) + 8) * STEPS / 16), 0, STEPS).astype(np.int64)

    def mixed(self, x: np.ndarray, gate: np.ndarray) -> np.ndarray:
        return np.clip((x * self.weights[gate]).sum(1), -12, 12)

    def learn_weights(self, batches: Iterator[tuple[np.ndarray, np.ndarray]], rate: float = 0.05) -> None:
        """Online gradient steps over (sequences, counts), each gate at a pace of its own."""
        slope = np.full_like(self.weights, 1e-4)
        for code, count in batches:
            for bit in range(7, -1, -1):
                x, gate, y = self.inputs(code, bit, leave_out=True)
                error = (y - 1 / (1 + np.exp(-self.mixed(x, gate)))) * count
                total = np.bincount(gate, count, GATES) + 1e-9
                step = np.stack([np.bincount(gate, error * x[:, j], GATES) for j in range(ORDERS + 1)], 1) / total[:, None]
                slope += step * step
                self.weights = self.weights + rate * step / np.sqrt(slope)

    def count_refinement(self, code: np.ndarray, count: np.ndarray) -> np.ndarray:
        """Observed bits by gate and mixed prediction: (2, GATES * (STEPS + 1))."""
        out = np.zeros((2, GATES * (STEPS + 1)))
        for bit in range(8):
            x, gate, y = self.inputs(code, bit, leave_out=True)
            at = gate * (STEPS + 1) + self.bucket(self.mixed(x, gate))
            out += [np.bincount(at, count * ~y, out.shape[1]), np.bincount(at, count * y, out.shape[1])]
        return out

    def set_refinement(self, seen: np.ndarray) -> None:
        """Where little was seen the map stays near the identity."""
        centre = 1 / (1 + np.exp(-(np.arange(STEPS + 1) * 16 / STEPS - 8)))
        own = np.tile(centre, GATES)
        self.refine = (seen[1] + 32 * own) / (seen.sum(0) + 32)

    def scorer(self) -> BitScorer:
        return BitScorer(*BitScorer.tables(self.n0, self.n1), self.weights, self.refine)


class BitScorer:
    """The learned model, ready to score: stretched predictions and seen classes by slot."""

    RECALL = 21

    def __init__(self, stretch: np.ndarray, seen: np.ndarray, weights: np.ndarray, refine: np.ndarray):
        self.stretch, self.seen, self.weights, self.refine = stretch, seen, weights.astype(np.float32), refine.astype(np.float32)
        self.known, self.known_bits = np.full(1 << self.RECALL, -1, np.int64), np.zeros(1 << self.RECALL, np.float32)

    @staticmethod
    def tables(n0: np.ndarray, n1: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        total = n0 + n1
        seen = np.searchsorted(_SEEN4, total, "right") * (len(_SEEN3) + 1) + np.searchsorted(_SEEN3, total, "right")
        return np.log((n1 + np.float32(0.05)) / (n0 + np.float32(0.05))).astype(np.float32), seen.astype(np.uint8)

    def log2(self, codes: np.ndarray, block: int = 1 << 15) -> np.ndarray:
        """log2 of the probability of each sequence's last byte after the others."""
        out, wide = np.empty(len(codes)), len(_SEEN3) + 1
        for lo in range(0, len(codes), block):
            code = codes[lo : lo + block]
            contexts, total = BitMixer.contexts(code), np.zeros(len(code))
            for bit in range(7, -1, -1):
                at = BitMixer.slots(contexts, code, bit, len(self.stretch))
                gate = (self.seen[at[-1]] // wide * wide + self.seen[at[-2]] % wide).astype(np.int64) * 8 + bit
                weights = self.weights[gate]
                m = weights[:, ORDERS] * np.float32(0.3)
                for o in range(ORDERS):
                    m += weights[:, o] * self.stretch[at[o]]
                m = np.clip(m, -12, 12)
                p = (1 / (1 + np.exp(-m)) + self.refine[gate * (STEPS + 1) + BitMixer.bucket(m)]) / 2
                p = np.clip(p, 1e-6, 1 - 1e-6)
                total += np.log2(np.where((code >> bit) & 1, p, 1 - p))
            out[lo : lo + block] = total
        return out

    def recalled(self, codes: np.ndarray) -> np.ndarray:
        """As ``log2``; each slot of a table keeps the sequence met last, so most aren't computed again."""
        with np.errstate(over="ignore"):
            slot = ((codes.view(np.uint64) * _C1) >> np.uint64(64 - self.RECALL)).view(np.int64)
        bits = self.known_bits[slot]
        new = np.flatnonzero(self.known[slot] != codes)
        if len(new):
            at, unique = pd.factorize(codes[new])
            fresh = self.log2(unique).astype(np.float32)
            bits[new] = fresh[at]
            place = slot[new]
            self.known[place], self.known_bits[place] = codes[new], bits[new]
        return bits

    def log10_of(self, streams: list[bytes], chunk: int = 1 << 21) -> np.ndarray:
        """log10 probability of each stream, a chunk of streams at a time."""
        out, lo = np.zeros(len(streams)), 0
        while lo < len(streams):
            hi, size = lo, 0
            while hi < len(streams) and (hi == lo or size + len(streams[hi]) <= chunk):
                size += len(streams[hi])
                hi += 1
            code, bounds = _padded(streams[lo:hi])
            bits = self.recalled(code)
            # the last bound may be the end of all, which no sum starts at
            sums = np.add.reduceat(bits, bounds.ravel()[:-1], dtype=np.float64)[::2]
            out[lo:hi] = sums * math.log10(2)
            lo = hi
        return out


#: the table that this process read last, by path and form
_HELD: dict[tuple[str, bool], tuple[np.ndarray, np.ndarray]] = {}


def _counting(kernel):
    """A kernel that needs no table: one that an earlier run left in this process goes, and what the task held goes back."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _HELD.clear()
        yield from kernel(batches)

    return trimmed(run)


def _counted_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Words of this task's texts with their counts; an empty word counts the ends."""
    seen: Counter = Counter()

    def out():
        return pa.RecordBatch.from_arrays([pa.array([w.decode("utf-8", "replace") for w in seen], pa.string()), pa.array(seen.values(), pa.int64())], ["word", "n"])

    for batch in batches:
        for text in batch.column(0):
            seen.update(words_of(text.as_py()))
        seen[b""] += batch.num_rows
        if len(seen) > 300_000:
            yield out()
            seen.clear()
    if seen:
        yield out()


def _counted_grams(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Byte sequences of this task's texts with their counts, summed as long as they fit."""
    held: list[tuple[np.ndarray, np.ndarray]] = []

    def summed(held):
        codes, at = np.unique(np.concatenate([c for c, _ in held]), return_inverse=True)
        return codes, np.bincount(at, np.concatenate([n for _, n in held]), len(codes)).astype(np.int64)

    def out(codes, counts):
        return pa.RecordBatch.from_arrays([pa.array(codes), pa.array(counts)], ["gram", "n"])

    def taken(streams):
        at, unique = pd.factorize(grams(streams))
        held.append((unique, np.bincount(at, minlength=len(unique))))
        if sum(len(c) for c, _ in held) > 1_500_000:
            held[:] = [summed(held)]

    for batch in batches:
        streams, size = [], 0
        for text in batch.column(0):
            streams.append(stream(words_of(text.as_py())))
            size += len(streams[-1])
            if size > 4 << 20:
                taken(streams)
                streams, size = [], 0
        if streams:
            taken(streams)
        if len(held) == 1 and len(held[0][0]) > 1_000_000:
            yield out(*held.pop())
    if held:
        yield out(*summed(held))


def _shards(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, Iterator[tuple[np.ndarray, np.ndarray]]]]:
    """(shard, its sequences and counts in steps) of rows (shard, gram, n) that lie in the order of shards."""
    held: list[tuple[np.ndarray, ...]] = []
    source = ((b.column(0).to_numpy(), b.column(1).to_numpy(), b.column(2).to_numpy().astype(float)) for b in batches if b.num_rows)

    def steps(shard: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        code, count = np.empty(0, np.int64), np.empty(0)
        while True:
            part = held.pop() if held else next(source, None)
            if part is None:
                break
            end = int(np.searchsorted(part[0], shard, "right"))
            code, count = np.concatenate([code, part[1][:end]]), np.concatenate([count, part[2][:end]])
            while len(code) >= STEP:
                yield code[:STEP], count[:STEP]
                code, count = code[STEP:], count[STEP:]
            if end < len(part[0]):
                held.append(tuple(x[end:] for x in part))
                break
        if len(code):
            yield code, count

    while True:
        if not held:
            first = next(source, None)
            if first is None:
                return
            held.append(first)
        shard = int(held[0][0][0])
        yield shard, steps(shard)


def _node_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Nodes of this task's sequences with how often a 0 and a 1 came next, summed as long as they fit."""
    held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

    def summed():
        nodes, at = np.unique(np.concatenate([h[0] for h in held]), return_inverse=True)
        return nodes, *(np.bincount(at, np.concatenate([h[j] for h in held]), len(nodes)) for j in (1, 2))

    def out(nodes, n0, n1):
        for lo in range(0, len(nodes), 1 << 18):
            some = slice(lo, lo + (1 << 18))
            yield pa.RecordBatch.from_arrays([pa.array(nodes[some].view(np.int64)), pa.array(n0[some]), pa.array(n1[some])], ["node", "n0", "n1"])

    for batch in batches:
        code, count = batch.column(0).to_numpy(), batch.column(1).to_numpy().astype(float)
        contexts = BitMixer.contexts(code)
        for bit in range(8):
            y = (code >> bit) & 1
            held += [(nodes, count * (1 - y), count * y) for nodes in BitMixer.nodes(contexts, code, bit)]
        if sum(len(h[0]) for h in held) > 1_500_000:
            held[:] = [summed()]
        if len(held) == 1 and len(held[0][0]) > 1_000_000:
            yield from out(*held.pop())
    if held:
        yield from out(*summed())


def _table_of(path: str, size: int, ready: bool) -> tuple[np.ndarray, np.ndarray]:
    """The written counts as (n0, n1) by slot, or ``ready`` to score; an empty slot is all zeros in both.

    Counts are floats of four bytes, as in the scores: exact to 2^24, beyond that to seven digits.
    """
    if (path, ready) not in _HELD:
        _HELD.clear()
        store, root = _store(path)
        table = np.zeros(size, np.float32), np.zeros(size, np.uint8 if ready else np.float32)
        for info in store.get_file_info(fs.FileSelector(root)):
            if info.base_name.endswith(".parquet"):
                with store.open_input_file(info.path) as f:
                    for batch in pq.ParquetFile(f).iter_batches(1 << 18):
                        at, n0, n1 = (batch.column(j).to_numpy() for j in range(3))
                        table[0][at], table[1][at] = BitScorer.tables(n0, n1) if ready else (n0, n1)
        _HELD[path, ready] = table
    return _HELD[path, ready]


def _learn(docs: DataFrame, text_col: str) -> tuple[str, int, BitMixer]:
    """Path and number of slots of the table of counts, and the model without it."""
    spark = docs.sparkSession
    scratch = Scratch(spark, "mixlm")
    counted = need(docs, text_col).mapInArrow(_counting(_counted_grams), "gram long, n long").groupBy("gram").agg(F.sum("n").alias("n"))
    # sequences that share the three bytes before the last meet, so most nodes are summed where they are found
    shared = scratch.keep(counted.repartition(F.expr("shiftright(gram, 8) & 16777215")), "grams")
    nodes = scratch.keep(shared.mapInArrow(_counting(_node_counts), "node long, n0 double, n1 double").groupBy("node").agg(F.sum("n0").alias("n0"), F.sum("n1").alias("n1")), "nodes")
    size = max(LEAST_SLOTS, ROOM * nodes.count())
    if size >= 1 << 31:
        raise ValueError(f"{size} slots are more than a worker's table can have")
    slot = F.shiftrightunsigned(F.shiftrightunsigned("node", 33) * F.lit(size), 31).cast("int").alias("slot")
    slots = scratch.keep(nodes.groupBy(slot).agg(F.sum("n0").alias("n0"), F.sum("n1").alias("n1")), "slots")
    path = scratch.paths[id(slots)]
    scratch.drop(nodes)
    model = BitMixer(None, None)

    shards = max(1, -(-shared.count() // SHARD))
    cut = shared.select(F.pmod(F.xxhash64("gram"), F.lit(shards)).alias("shard"), "gram", "n")
    cut = cut.repartition(shards, "shard").sortWithinPartitions("shard", F.xxhash64("gram", F.lit(1)), "gram")

    def weights(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for shard, steps in _shards(batches):
            mine, total = BitMixer(*_table_of(path, size, False)), 0.0

            def counted(steps=steps):
                nonlocal total
                for code, count in steps:
                    total += float(count.sum())
                    yield code, count

            mine.learn_weights(counted())
            yield pa.RecordBatch.from_arrays([pa.array([shard], pa.int64()), pa.array([total]), pa.array([mine.weights.ravel().tolist()])], ["shard", "n", "values"])

    rows = sorted(cut.mapInArrow(trimmed(weights), "shard long, n double, values array<double>").collect(), key=lambda r: r.shard)
    if rows:
        model.weights = (sum(r.n * np.array(r["values"]) for r in rows) / sum(r.n for r in rows)).reshape(model.weights.shape)
    chosen = model.weights

    def refinement(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mine, total = BitMixer(*_table_of(path, size, False), chosen), None
        for batch in batches:
            part = mine.count_refinement(batch.column(0).to_numpy(), batch.column(1).to_numpy().astype(float))
            total = part if total is None else total + part
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([total.ravel().tolist()])], ["values"])

    parts = shared.mapInArrow(trimmed(refinement), "values array<double>").collect()
    model.set_refinement(sum((np.array(r["values"]) for r in parts), np.zeros(2 * GATES * (STEPS + 1))).reshape(2, -1))
    scratch.drop(shared)
    return path, size, model


def train(docs: DataFrame, *, text_col: str = "text") -> BitMixer:
    """The model of all rows of ``docs``; null texts count as empty ones."""
    path, size, model = _learn(docs, text_col)
    model.n0, model.n1 = _table_of(path, size, False)
    _HELD.clear()
    delete_path(docs.sparkSession, path)
    return model


def _least_count(vocabulary: DataFrame, frequent: int) -> int:
    """Least count that no more than ``frequent`` words reach; counts are few and grow apart."""
    edges = [2**i for i in range(62)]
    reach = vocabulary.agg(*[F.count_if(F.col("n") >= e).alias(str(e)) for e in edges]).first()
    return next(e for e, some in zip([*edges, 1 << 62], [*reach, 0], strict=True) if some <= frequent)


def lm_scores(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", frequent: int = 1 << 17) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, bits_per_byte) per row.

    Rows whose id's checksum is 0 modulo 10 are held out, all others teach; a
    row with a null id teaches. ``base_score`` sums log10 of smoothed unigram
    shares over words and one end; ``score`` is the model's log10 probability
    of the same tokens, ``bits_per_byte`` that in bits a byte of the sequence.
    Null texts count as empty: an end alone. The ``frequent`` commonest words
    are sent to the workers; all others are looked up by a join. Rows are
    judged each by itself, whatever their ids. Other columns are ignored.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "lmscore")
    own = need(docs, id_col, text_col).toDF("doc_id", "text")
    teach = own.where("coalesce(crc32(cast(cast(doc_id as string) as binary)) % 10, 1) <> 0")
    vocabulary = scratch.keep(teach.select("text").mapInArrow(_counting(_counted_words), "word string, n long").groupBy("word").agg(F.sum("n").alias("n")), "words")
    total, distinct = vocabulary.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
    floor = total + 0.1 * (distinct + 1)
    least = _least_count(vocabulary, frequent)
    often = vocabulary.where(F.col("n") >= least).toArrow()
    # of the frequent words the workers need the logarithm only
    log = {w.encode(): math.log10((n + 0.1) / floor) for w, n in zip(often.column("word").to_pylist(), often.column("n").to_pylist(), strict=True)}
    complete = distinct <= len(log)
    path, size, model = _learn(teach, "text")
    sent = spark.sparkContext.broadcast((log, model.weights, model.refine))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        log, *learned = sent.value
        judge, number = BitScorer(*_table_of(path, size, True), *learned), TaskContext.get().partitionId() << 40
        never = math.log10(0.1 / floor)
        for whole in batches:
            for lo in range(0, whole.num_rows, 1250):
                batch = whole.slice(lo, 1250)
                rows, rare, streams = [], [], []
                for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                    words = words_of(text.as_py())
                    streams.append(stream(words))
                    words.append(b"")
                    values = list(map(log.get, words))
                    lost = values.count(None)
                    base = sum(v for v in values if v is not None) if lost else sum(values)
                    if lost and complete:
                        base += lost * never
                    elif lost:
                        times = Counter(w for w, v in zip(words, values, strict=True) if v is None)
                        rare += [(number, w.decode("utf-8", "replace"), n) for w, n in times.items()]
                    rows.append((number, doc_id, held_out(doc_id), len(words), len(words) - lost, float(base), len(streams[-1])))
                    number += 1
                score = judge.log10_of(streams)
                n, m = len(rows), len(rare)
                c = list(zip(*rows, strict=True))
                at, w, times = zip(*rare, strict=True) if rare else ((), (), ())
                blank = [None] * m
                yield pa.RecordBatch.from_arrays(
                    [pa.array([*c[0], *at], pa.int64()), pa.array([*c[1], *blank], pa.int64()), pa.array([*c[2], *blank], pa.bool_()), pa.array([*c[3], *blank], pa.int64()), pa.array([*c[4], *blank], pa.int64()), pa.array([*c[5], *blank], pa.float64()), pa.array([*score, *blank], pa.float64()), pa.array([*c[6], *blank], pa.int64()), pa.array([*[None] * n, *w], pa.string()), pa.array([*[None] * n, *times], pa.int64())],
                    ["row", "doc_id", "held_out", "n_tokens", "known", "base", "score", "n_bytes", "word", "times"],
                )

    judged = scratch.keep(own.mapInArrow(trimmed(run), "row long, doc_id long, held_out boolean, n_tokens long, known long, base double, score double, n_bytes long, word string, times long"), "judged")
    delete_path(spark, path)
    rows = judged.where("word is null")
    asked = judged.where("word is not null").select("row", "word", "times")
    found = asked.join(vocabulary, "word", "left")
    value = F.log10((F.coalesce("n", F.lit(0)) + F.lit(0.1)) / F.lit(floor))
    rare = found.groupBy("row").agg(F.sum(value * F.col("times")).alias("more"), F.coalesce(F.sum(F.when(F.col("n").isNotNull(), F.col("times"))), F.lit(0)).alias("more_known"))
    out = rows.join(rare, "row", "left")
    return out.select(
        "doc_id", "held_out", "n_tokens", (F.col("known") + F.coalesce("more_known", F.lit(0))).alias("n_known"), F.lit(total).cast("long").alias("train_tokens"),
        (F.col("base") + F.coalesce("more", F.lit(0.0))).alias("base_score"), "score", (-F.col("score") * math.log2(10) / F.col("n_bytes")).alias("bits_per_byte"),
    )

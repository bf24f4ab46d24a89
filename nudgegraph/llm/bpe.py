"""Byte-level BPE with a two-tier lookup.

Tier one is a minimal perfect hash over the vocabulary: one displacement a
bucket and one slot a token, checked against the token's bytes. A pre-token
that it resolves is a token already. Tier two merges the bytes of all others:
a heap of pairs by rank over a linked list of parts, so a pre-token of n bytes
costs n log n however long it is.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
import xxhash
from pyspark.sql import DataFrame

from nudgegraph.llm.text import need, trimmed

_A, _B = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, filter(bytes.strip, lines))}


def _hashes(keys: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh3_64_intdigest, keys), np.uint64, len(keys))


def _slots(h: np.ndarray, d: np.ndarray, n: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = (h ^ (d * _A)) * _B
        x ^= x >> np.uint64(31)
        return ((x * _A) >> np.uint64(32)) % np.uint64(n)


class PerfectHash:
    """Hash and displace; lone keys take what slots are left, directly."""

    def __init__(self, keys: list[bytes], per_bucket: int = 4):
        self.n, self.n_buckets = len(keys), max(1, len(keys) // per_bucket)
        h = _hashes(keys)
        if len(np.unique(h)) != len(keys):
            raise ValueError("keys repeat")
        bucket = (h % np.uint64(self.n_buckets)).astype(np.int64)
        order = np.argsort(bucket, kind="stable")
        bounds = np.searchsorted(bucket[order], np.arange(self.n_buckets + 1))
        self.move = np.zeros(self.n_buckets, np.int64)
        self.key_at = np.full(self.n, -1, np.int64)
        taken = np.zeros(self.n, bool)
        sizes = np.diff(bounds)
        free = None
        for b in np.argsort(-sizes, kind="stable"):
            mine = order[bounds[b] : bounds[b + 1]]
            if len(mine) == 0:
                break
            if len(mine) == 1:
                free = np.flatnonzero(~taken)[::-1].tolist() if free is None else free
                slot = free.pop()
                self.move[b], self.key_at[slot] = -slot - 1, mine[0]
                continue
            first = 0
            while True:
                tries = np.arange(first, first + 64, dtype=np.uint64)
                at = _slots(h[mine][None, :], tries[:, None], self.n).astype(np.int64)
                good = ~taken[at].any(1) & (np.diff(np.sort(at, 1), axis=1) > 0).all(1)
                if good.any():
                    i = int(np.argmax(good))
                    self.move[b] = first + i
                    taken[at[i]] = True
                    self.key_at[at[i]] = mine
                    break
                first += 64

    @classmethod
    def of(cls, move: np.ndarray, key_at: np.ndarray) -> PerfectHash:
        """The same table from its two arrays."""
        table = cls.__new__(cls)
        table.n, table.n_buckets, table.move, table.key_at = len(key_at), len(move), move, key_at
        return table

    def find(self, keys: list[bytes]) -> np.ndarray:
        """For each key the number of the only key that it can be."""
        h = _hashes(keys)
        move = self.move[(h % np.uint64(self.n_buckets)).astype(np.int64)]
        hashed = _slots(h, np.maximum(move, 0).astype(np.uint64), self.n).astype(np.int64)
        return self.key_at[np.where(move < 0, -move - 1, hashed)]


class Coder:
    """Encodes and decodes texts; remembers the pre-tokens met most recently."""

    def __init__(self, tokens: list[bytes], ids: list[int], table: PerfectHash, pattern: str, known: dict[str, tuple[str, int, bytes]] | None = None, remember: int = 500_000):
        self.tokens, self.ids, self.table, self.remember = tokens, ids, table, remember
        self.rank = dict(zip(tokens, ids, strict=True))
        self.bytes_of = dict(zip(ids, tokens, strict=True))
        self.split = regex.compile(pattern).findall
        self.known = {} if known is None else known

    def merge(self, word: bytes) -> list[int]:
        """Ids of a pre-token that isn't a token: always the leftmost pair of least rank."""
        rank, n = self.rank, len(word)
        after, before, end = list(range(1, n + 1)), list(range(-1, n - 1)), list(range(1, n + 1))
        heap = [(r, i, i + 2) for i in range(n - 1) if (r := rank.get(word[i : i + 2])) is not None]
        heapq.heapify(heap)
        while heap:
            _, i, stop = heapq.heappop(heap)
            # stale: i was merged away, or a part of the pair has grown since
            if end[i] == 0 or (j := after[i]) >= n or end[j] != stop or end[i] != j:
                continue
            end[i], end[j] = stop, 0
            after[i] = k = after[j]
            if k < n:
                before[k] = i
                if (r := rank.get(word[i : end[k]])) is not None:
                    heapq.heappush(heap, (r, i, end[k]))
            if (p := before[i]) >= 0 and (r := rank.get(word[p:stop])) is not None:
                heapq.heappush(heap, (r, p, stop))
        out, i = [], 0
        while i < n:
            out.append(rank[word[i : end[i]]])
            i = after[i]
        return out

    def learn(self, pre: list[str]) -> None:
        new = list(dict.fromkeys(t for t in pre if t not in self.known))
        if not new:
            return
        if len(self.known) + len(new) > self.remember:
            self.known.clear()
            new = list(dict.fromkeys(pre))
        raw = [t.encode("utf-8", "surrogatepass") for t in new]
        for text, word, at in zip(new, raw, self.table.find(raw).tolist(), strict=True):
            ids = [self.ids[at]] if at >= 0 and self.tokens[at] == word else self.merge(word)
            self.known[text] = " ".join(map(str, ids)), len(ids), self.decode(ids)

    def encode(self, text: str | None) -> list[int]:
        pre = self.split(text or "")
        self.learn(pre)
        return [int(i) for t in pre for i in self.known[t][0].split()]

    def decode(self, ids: list[int]) -> bytes:
        of = self.bytes_of
        return b"".join([of[i] for i in ids])

    def digests(self, text: str | None) -> tuple[int, str, str]:
        pre = self.split(text or "")
        self.learn(pre)
        parts = [self.known[t] for t in pre]
        return sum([p[1] for p in parts]), hashlib.sha256(" ".join([p[0] for p in parts]).encode()).hexdigest(), hashlib.sha256(b"".join([p[2] for p in parts])).hexdigest()


def vocabulary(path: str) -> tuple[list[bytes], list[int], PerfectHash]:
    ranks = read_ranks(path)
    tokens = list(ranks)
    return tokens, list(ranks.values()), PerfectHash(tokens)


def _shared(docs: DataFrame, path: str, pattern: str, remember: int = 500_000):
    """The vocabulary is sent once to each executor: its size is the file's.

    Plain arrays are sent, so executors need no module of ours; the empty dict
    at the end lives as long as a worker and keeps pre-tokens between tasks.
    """
    tokens, ids, table = vocabulary(path)
    sent = docs.sparkSession.sparkContext.broadcast((tokens, ids, table.move, table.key_at, {}))

    def coder() -> Coder:
        tokens, ids, move, key_at, known = sent.value
        return Coder(tokens, ids, PerfectHash.of(move, key_at), pattern, known, remember)

    return coder


def bpe_digests(docs: DataFrame, ranks_path: str, pattern: str, *, id_col: str = "doc_id", text_col: str = "text", remember: int = 500_000) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) for every row of ``docs``.

    Texts are encoded whole, each match of ``pattern`` by itself and without
    special tokens, and decoded again. A null text counts as an empty one.
    Repeated and null ids are kept as they are; other columns are ignored. A
    worker remembers ``remember`` pre-tokens between tasks.
    """
    coder = _shared(docs, ranks_path, pattern, remember)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        code = coder()
        for batch in batches:
            rows = [code.digests(text.as_py()) for text in batch.column(1)]
            n, ids, back = zip(*rows, strict=True) if rows else ((), (), ())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(ids, pa.string()), pa.array(back, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return need(docs, id_col, text_col).toDF("doc_id", "text").mapInArrow(trimmed(run), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def bpe_encode(docs: DataFrame, ranks_path: str, pattern: str, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, ids array<int>) for every row; null texts count as empty."""
    coder = _shared(docs, ranks_path, pattern)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        code = coder()
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([code.encode(t.as_py()) for t in batch.column(1)], pa.list_(pa.int32()))], ["doc_id", "ids"])

    return need(docs, id_col, text_col).toDF("doc_id", "text").mapInArrow(run, "doc_id long, ids array<int>")


def bpe_decode(coded: DataFrame, ranks_path: str, pattern: str, *, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """(doc_id, bytes binary) for every row of ids; null ids count as none.

    An id outside the vocabulary raises an error.
    """
    coder = _shared(coded, ranks_path, pattern)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        code = coder()
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([code.decode(x.as_py() or []) for x in batch.column(1)], pa.binary())], ["doc_id", "bytes"])

    return need(coded, id_col, ids_col).toDF("doc_id", "ids").mapInArrow(run, "doc_id long, bytes binary")

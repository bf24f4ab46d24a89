"""Benchmark decontamination by multi-pattern search over words.

Patterns are windows of benchmark words. For patterns of one length a table
maps each block of two neighbouring words to how far the search may move on;
a block in no pattern lets it pass almost a whole window unread. Where the
table says nought, the block's bucket names the patterns that end with it;
those that begin like the text are compared word by word.
"""

from __future__ import annotations

import hashlib
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nudgegraph.llm.text import need, trimmed
from nudgegraph.session import Scratch

# fixed: bytes outside words become blanks, A-Z become lower case, all other word bytes stay
_TABLE = bytes(c if 0x30 <= c <= 0x39 or 0x61 <= c <= 0x7A or c >= 0x80 else c + 32 if 0x41 <= c <= 0x5A else 0x20 for c in range(256))


def plain_words(text: str | None) -> list[bytes]:
    return [] if text is None else text.encode("utf-8", "surrogatepass").translate(_TABLE).split()


class PatternSearch:
    """Shift tables and buckets for each pattern length."""

    def __init__(self, items: list[tuple[str, str | None]], window: int):
        self.names = sorted({name for name, _ in items})
        number = {name: i for i, name in enumerate(self.names)}
        by_length: dict[int, dict[tuple, set[int]]] = {}
        for name, text in items:
            w = plain_words(text)
            length = min(window, len(w))
            for i in range(len(w) - length + 1 if w else 0):
                by_length.setdefault(length, {}).setdefault(tuple(w[i : i + length]), set()).add(number[name])
        self.classes = [self._tables(length, patterns) for length, patterns in sorted(by_length.items())]

    @staticmethod
    def _tables(length: int, patterns: dict[tuple, set[int]]):
        block = min(2, length)
        shift: dict[tuple, int] = {}
        bucket: dict[tuple, dict[tuple, list]] = {}
        for pattern, owners in patterns.items():
            for end in range(block, length + 1):
                b = pattern[end - block : end]
                shift[b] = min(shift.get(b, length), length - end)
            bucket.setdefault(pattern[-block:], {}).setdefault(pattern[:block], []).append((pattern, sorted(owners)))
        return length, block, length - block + 1, shift, bucket

    def find(self, words: list[bytes], spans: list[tuple[int, int]], owners: set[int]) -> None:
        """Adds every occurrence to ``spans`` and the items found to ``owners``."""
        n = len(words)
        for length, block, far, shift, bucket in self.classes:
            end, get = length, shift.get
            while end <= n:
                b = tuple(words[end - block : end])
                move = get(b, far)
                if move:
                    end += move
                    continue
                start = end - length
                for pattern, own in bucket[b].get(tuple(words[start : start + block]), ()):
                    if tuple(words[start:end]) == pattern:
                        spans.append((start, end))
                        owners.update(own)
                end += 1


def _covered(spans: list[tuple[int, int]]) -> int:
    total, upto = 0, 0
    for start, end in sorted(spans):
        total += max(0, end - max(start, upto))
        upto = max(upto, end)
    return total


#: the tables that this process built last, by name
_BUILT: dict[str, PatternSearch] = {}


def _built(sent, window: int) -> PatternSearch:
    """The tables of the broadcast (name, items), built once in a process."""
    name, items = sent.value
    if name not in _BUILT:
        _BUILT.clear()
        _BUILT[name] = PatternSearch(items, window)
    return _BUILT[name]


def _hits(sent, window: int):
    """(row, spans, items) of rows in which something occurs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        search = _built(sent, window)
        for batch in batches:
            rows, flat, lists = [], [], []
            for row, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                spans, owners = [], set()
                search.find(plain_words(text.as_py()), spans, owners)
                if spans:
                    rows.append(row)
                    flat.append([x for s in spans for x in s])
                    lists.append([search.names[i] for i in owners])
            yield pa.RecordBatch.from_arrays([pa.array(rows, pa.int64()), pa.array(flat, pa.list_(pa.int32())), pa.array(lists, pa.list_(pa.string()))], ["row", "spans", "items"])

    return run


def _judged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        n, hit, count, digest = [], [], [], []
        for text, flat, items in zip(batch.column("text"), batch.column("spans"), batch.column("items"), strict=True):
            flat, names = flat.as_py() or [], sorted(set(items.as_py() or ()))
            n.append(len(plain_words(text.as_py())))
            hit.append(_covered(list(zip(flat[::2], flat[1::2], strict=True))))
            count.append(len(names))
            digest.append(hashlib.sha256(",".join(names).encode()).hexdigest())
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(hit, pa.int64()), pa.array(count, pa.int64()), pa.array(digest), pa.array([x > 0 for x in hit]), *batch.columns[4:]], ["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated", *batch.schema.names[4:]])


def _fused(sent, window: int):
    """Search and verdict in one pass, for a benchmark that fits one shard."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        search = _built(sent, window)
        for batch in batches:
            n, hit, count, digest = [], [], [], []
            for text in batch.column(1):
                words, spans, owners = plain_words(text.as_py()), [], set()
                search.find(words, spans, owners)
                n.append(len(words))
                hit.append(_covered(spans))
                count.append(len(owners))
                digest.append(hashlib.sha256(",".join(search.names[i] for i in sorted(owners)).encode()).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(hit, pa.int64()), pa.array(count, pa.int64()), pa.array(digest), pa.array([x > 0 for x in hit]), *batch.columns[2:]], ["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated", *batch.schema.names[2:]])

    return run


VERDICT = "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean"


def decontaminate(docs: DataFrame, benchmark: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", window: int = 10, shard_bytes: int = 16 << 20, carry: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, n_words, n_hit, n_items, items_sha256, contaminated, *carry) per row of ``docs``.

    A word is hit where it lies inside an occurrence of ``window`` consecutive
    words of an item; an item of fewer words counts whole. Only a shard of the
    benchmark of about ``shard_bytes`` of text is sent to the executors at a
    time; a larger benchmark takes one pass over the texts for each shard, which
    writes hits alone.

    Null and empty texts have no words. Items without words or with a null id
    take no part; rows that repeat an item id are one item. Rows of ``docs``
    are judged each by itself, whatever their ids. Other columns than ``carry`` are ignored.
    """
    scratch = Scratch(docs.sparkSession, "decontaminate")
    own = need(docs, id_col, text_col, *carry).toDF("doc_id", "text", *[f"carry_{c}" for c in carry])
    carried = "".join(f", `carry_{c}` {docs.schema[c].dataType.simpleString()}" for c in carry)
    back = [F.col(f"carry_{c}").alias(c) for c in carry]
    plain = ["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"]
    items = need(benchmark, item_col, item_text_col).toDF("item", "text").select(F.col("item").cast("string"), "text").where("item is not null and text is not null")
    total = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    shards = max(1, -(-total // shard_bytes))
    context = docs.sparkSession.sparkContext
    if shards == 1:
        sent = context.broadcast((uuid.uuid4().hex, [tuple(r) for r in items.collect()]))
        return own.mapInArrow(trimmed(_fused(sent, window)), VERDICT + carried).select(*plain, *back)
    items = scratch.keep(items.withColumn("shard", F.pmod(F.xxhash64("item", "text"), F.lit(shards))), "items")
    own = scratch.keep(own.withColumn("row", F.monotonically_increasing_id()), "rows")
    found = None
    for i in range(shards):
        sent = context.broadcast((uuid.uuid4().hex, [tuple(r) for r in items.where(F.col("shard") == i).select("item", "text").collect()]))
        part = scratch.keep(own.select("row", "text").mapInArrow(_hits(sent, window), "row long, spans array<int>, items array<string>"), "hits")
        sent.destroy()
        found = part if found is None else found.unionByName(part)
    found = found.groupBy(F.col("row").alias("of")).agg(F.flatten(F.collect_list("spans")).alias("spans"), F.array_distinct(F.flatten(F.collect_list("items"))).alias("items"))
    found = own.join(found, F.col("row") == F.col("of"), "left").select("doc_id", "text", "spans", "items", *[f"carry_{c}" for c in carry])
    return found.mapInArrow(_judged, VERDICT + carried).select(*plain, *back)


ORACLE = r"""
with doc_words as (
  select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w
  from documents
), item_words as (
  select item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w
  from benchmark
), windows as (
  select distinct item_id, least(len(w), 10) as n, array_to_string(w[i : i + least(len(w), 10) - 1], ' ') as win
  from (select item_id, w, unnest(range(1, greatest(len(w) - 9, 1) + 1)) as i from item_words where len(w) > 0)
), lengths as (select distinct n from windows),
places as (
  select doc_id, w, n, unnest(range(1, len(w) - n + 2)) as i
  from doc_words, lengths where len(w) >= n
), occurrences as (
  select p.doc_id, p.i, p.n, x.item_id
  from (select doc_id, i, n, array_to_string(w[i : i + n - 1], ' ') as win from places) p join windows x on x.n = p.n and x.win = p.win
), hit as (
  select doc_id, count(distinct j) as n_hit from (select doc_id, unnest(range(i, i + n)) as j from occurrences) group by doc_id
), named as (
  select doc_id, count(*) as n_items, string_agg(item, ',' order by item) as names
  from (select distinct doc_id, item_id::varchar as item from occurrences) group by doc_id
)
select d.doc_id, len(d.w)::bigint as n_words, coalesce(h.n_hit, 0)::bigint as n_hit, coalesce(m.n_items, 0)::bigint as n_items,
       sha256(coalesce(m.names, '')) as items_sha256, coalesce(h.n_hit, 0) > 0 as contaminated
from doc_words d left join hit h on h.doc_id = d.doc_id left join named m on m.doc_id = d.doc_id
"""

"""Substring deduplication over sliding spans of sentences.

A text is tiled into pieces that end with sentence marks or line ends; pieces
with words are its sentences. Every run of ``sentences`` consecutive sentences
is a span, and so is a single sentence of at least ``words`` words. A span's
first occurrence, by (doc_id, place), stays; sentences that any other
occurrence covers are covered, and unbroken stretches of covered sentences that
have at least ``words`` words in all go.

A repeat inside a document is seen there and then, so each document sends each
span once; spans are computed once and kept as hashes. The join needs the
smallest document of a span only, which partial aggregation finds before the
shuffle; a span in a third of all documents is a skewed join key that adaptive
execution splits. A document's hits are hashes too, never places, so a row
loses only what it holds itself.

Runs of a given number of words are a second rule, blind to sentences: all
words go that lie in a run which an earlier place holds. The mark of a run is
the least hash of the short shingles in it, so equal runs have equal marks and
most neighbouring runs share theirs. Marks are joined first; only runs whose
mark occurs in two documents are hashed and joined themselves.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nudgegraph.llm.text import need, trimmed, words_of
from nudgegraph.session import Scratch

TILE = r"[^.!?\n]*[.!?\n]+|[^.!?\n]+"
_WORD = re.compile(r"[^\x20\x09-\x0D]+")
_BASE, _MASK = 0x9E3779B97F4A7C15, (1 << 64) - 1
_BACK = pow(_BASE, -1, 1 << 64)


def _tiles(text: str | None) -> tuple[list[str], list[int], list[bytes], list[int]]:
    """All pieces; of those with words: places, digests and numbers of words."""
    tiles = [] if text is None else re.findall(TILE, text)
    at, digest, size = [], [], []
    for i, tile in enumerate(tiles):
        words = tile.encode("utf-8", "surrogatepass").lower().split()
        if words:
            at.append(i)
            digest.append(xxhash.xxh3_64_digest(b" ".join(words)))
            size.append(len(words))
    return tiles, at, digest, size


def _spans(digest: list[bytes], size: list[int], sentences: int, words: int) -> list[tuple[int, int, int]]:
    """(start, end, hash) of every span, by start; end is exclusive."""
    joined, out = b"".join(digest), []
    for start, n in enumerate(size):
        for end in ((start + 1, start + sentences) if n >= words and sentences > 1 else (start + sentences,)):
            if end <= len(size):
                out.append((start, end, xxhash.xxh3_64_intdigest(joined[8 * start : 8 * end]) - (1 << 63)))
    return out


def _stretches(covered: set[int], size: list[int], words: int) -> set[int]:
    """Of the covered sentences those in unbroken stretches with enough words."""
    out, now, total = set(), [], 0
    for i in [*sorted(covered), -1]:
        if now and i != now[-1] + 1:
            if total >= words:
                out.update(now)
            now, total = [], 0
        now.append(i)
        total += size[i] if i >= 0 else 0
    return out


def _runs(text: str | None, run: int) -> tuple[np.ndarray, np.ndarray]:
    """(mark, hash) of the run of ``run`` words from each word on."""
    words = words_of(text)
    n = len(words)
    if n < run:
        return np.empty(0, np.int64), np.empty(0, np.int64)
    h = np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, n)
    with np.errstate(over="ignore"):
        up = np.cumprod(np.full(n, _BASE, np.uint64), dtype=np.uint64)
        back = np.cumprod(np.full(n, _BACK, np.uint64), dtype=np.uint64)
        sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(h * up, dtype=np.uint64)])

        def hashed(width: int) -> np.ndarray:
            x = (sums[width:] - sums[:-width]) * back[: n - width + 1]
            x = (x ^ (x >> np.uint64(32))) * np.uint64(0xBF58476D1CE4E5B9)
            return (x ^ (x >> np.uint64(29))).view(np.int64)

        short = max(1, run * 2 // 5)
        least, wide, most = hashed(short), 1, run - short + 1
        while wide < most:
            step = min(wide, most - wide)
            least, wide = np.minimum(least[:-step], least[step:]), wide + step
        return least, hashed(run)


def _marks_here(run: int):
    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            marks, ids, held = [], [], 0

            def out(marks=marks, ids=ids):
                ids = [pa.array([i] * len(m), pa.int64()) for i, m in zip(ids, marks, strict=True)]
                return pa.RecordBatch.from_arrays([pa.array(np.concatenate([np.empty(0, np.int64), *marks])), pa.concat_arrays(ids) if ids else pa.array([], pa.int64())], ["mark", "doc_id"])

            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                marks.append(np.unique(_runs(text.as_py(), run)[0]))
                ids.append(doc_id)
                held += len(marks[-1])
                if held > 200_000:
                    yield out()
                    marks.clear(), ids.clear()
                    held = 0
            yield out()

    return go


def _marked_runs(run: int):
    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for doc_id, text, marks in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2), strict=True):
                mark, whole = _runs(text.as_py(), run)
                found = np.unique(whole[np.isin(mark, marks.values.to_numpy())])
                for lo in range(0, len(found), 200_000):
                    some = found[lo : lo + 200_000]
                    yield pa.RecordBatch.from_arrays([pa.array(some), pa.array([doc_id] * len(some), pa.int64())], ["run", "doc_id"])

    return go


def _held_before(rows: DataFrame, key: str) -> DataFrame:
    """Rows of (key, doc_id, ...) whose key a row of a smaller doc_id has too."""
    firsts = rows.groupBy(key).agg(F.min("doc_id").alias("first_id"), F.count("*").alias("often")).where("often > 1").select(key, "first_id")
    return rows.join(firsts, key).where(~F.col("doc_id").eqNullSafe(F.col("first_id")))


def _run_hits(own: DataFrame, run: int) -> DataFrame:
    """(run_of, runs): each document's hashes of runs that an earlier document holds."""
    marks = own.mapInArrow(trimmed(_marks_here(run)), "mark long, doc_id long")
    shared = marks.join(marks.groupBy("mark").agg(F.count("*").alias("often")).where("often > 1").select("mark"), "mark")
    shared = shared.groupBy("doc_id").agg(F.collect_set("mark").alias("marks")).withColumnRenamed("doc_id", "of")
    asked = own.join(shared, F.col("doc_id").eqNullSafe(F.col("of"))).select("doc_id", "text", "marks")
    runs = asked.mapInArrow(trimmed(_marked_runs(run)), "run long, doc_id long")
    return _held_before(runs, "run").groupBy("doc_id").agg(F.collect_set("run").alias("runs")).withColumnRenamed("doc_id", "run_of")


def _covered(text: str | None, hits: np.ndarray, run: int) -> list[tuple[int, int]]:
    """Bounds in ``text`` of the words in runs that are in ``hits`` or lie wholly after an equal one here."""
    _, whole = _runs(text, run)
    if not len(whole):
        return []
    gone = np.isin(whole, hits)
    if len(whole) > run:
        _, first, same = np.unique(whole, return_index=True, return_inverse=True)
        gone |= np.arange(len(whole)) - first[same] >= run
    starts = np.flatnonzero(gone)
    if not len(starts):
        return []
    places = [m.span() for m in _WORD.finditer(text)]
    out, lo, hi = [], starts[0], starts[0] + run
    for at in starts[1:]:
        if at > hi:
            out.append((places[lo][0], places[hi - 1][1]))
            lo = at
        hi = at + run
    return [*out, (places[lo][0], places[hi - 1][1])]


def _first_here(sentences: int, words: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hashes, ids = [], []

            def out(hashes=hashes, ids=ids):
                return pa.RecordBatch.from_arrays([pa.array(hashes, pa.int64()), pa.array(ids, pa.int64())], ["span", "doc_id"])

            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                _, _, digest, size = _tiles(text.as_py())
                mine = {h for _, _, h in _spans(digest, size, sentences, words)}
                hashes.extend(mine)
                ids.extend([doc_id] * len(mine))
                if len(hashes) > 200_000:
                    yield out()
                    hashes.clear(), ids.clear()
            yield out()

    return run


def _less(tiles: list[str], covered: list[tuple[int, int]]) -> tuple[list[str], set[int]]:
    """The tiles without what is covered, and those of them that lost their last word by it."""
    out, emptied, begin, c = [], set(), 0, 0
    for i, tile in enumerate(tiles):
        end, at, left = begin + len(tile), begin, []
        while c < len(covered) and covered[c][0] < end:
            left.append(tile[at - begin : max(at, covered[c][0]) - begin])
            at = max(at, min(end, covered[c][1]))
            if covered[c][1] > end:
                break
            c += 1
        left.append(tile[at - begin :])
        out.append("".join(left))
        if at > begin and not _WORD.search(out[-1]):
            emptied.add(i)
        begin = end
    return out, emptied


def _without(sentences: int, words: int, length: int | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, count, gone_count = [], [], []
            for text, hits, runs in zip(batch.column(1), batch.column(2), batch.column(3), strict=True):
                text, hits = text.as_py(), set(hits.as_py() or ())
                tiles, at, digest, size = _tiles(text)
                seen, gone = set(), set()
                for start, end, h in _spans(digest, size, sentences, words):
                    if h in hits or h in seen:
                        gone.update(range(start, end))
                    seen.add(h)
                gone = _stretches(gone, size, words)
                cut = {at[i] for i in gone}
                covered = _covered(text, np.array(runs.as_py() or (), np.int64), length) if length else []
                if covered:
                    tiles, emptied = _less(tiles, covered)
                    gone.update(i for i, t in enumerate(at) if t in emptied)
                    text = "".join(tiles)
                texts.append(None if text is None else "".join(t for i, t in enumerate(tiles) if i not in cut) if cut else text)
                count.append(len(at))
                gone_count.append(len(gone))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string()), pa.array(count, pa.int64()), pa.array(gone_count, pa.int64()), *batch.columns[4:]], ["doc_id", "text", "n_sentences", "n_removed", *batch.schema.names[4:]])

    return run


def substring_dedup(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", sentences: int = 2, words: int = 20, run: int | None = None, carry: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, text, n_sentences, n_removed, *carry) for every row of ``docs``.

    ``text`` is what stays of the text, ``n_sentences`` and ``n_removed`` count
    sentences before and removed. Words lie between ASCII white space and are
    compared with A-Z lower-cased; pieces without words always stay. With
    ``run``, words go too that lie in a run of that many words which an earlier
    document, or an earlier place that it doesn't overlap, holds, wherever the
    sentences end; a sentence counts as removed when its last word goes.

    A null text stays null; empty texts stay empty; a document that is removed
    whole keeps its row with an empty text. Rows that repeat a ``doc_id`` count
    as one document, as do all rows with a null ``doc_id``, which come after
    all others; repeats between such rows stay, and each row loses only
    sentences of its own that a smaller id holds. Other columns than ``carry``
    are ignored. Empty tables give an empty result.
    """
    own = need(docs, id_col, text_col).toDF("doc_id", "text")
    spans = Scratch(docs.sparkSession, "substring").keep(own.mapInArrow(trimmed(_first_here(sentences, words)), "span long, doc_id long"), "spans")
    hits = _held_before(spans, "span").groupBy("doc_id").agg(F.collect_set("span").alias("hits")).withColumnRenamed("doc_id", "of")
    whole = need(docs, id_col, text_col, *carry).toDF("doc_id", "text", *carry)
    found = whole.join(hits, F.col("doc_id").eqNullSafe(F.col("of")), "left")
    if run:
        found = found.join(_run_hits(own, run), F.col("doc_id").eqNullSafe(F.col("run_of")), "left")
    found = found.select("doc_id", "text", "hits", F.col("runs") if run else F.lit(None).cast("array<long>").alias("runs"), *carry)
    kinds = {f.name: f.dataType.simpleString() for f in whole.schema.fields}
    schema = "doc_id long, text string, n_sentences long, n_removed long" + "".join(f", `{c}` {kinds[c]}" for c in carry)
    return found.mapInArrow(trimmed(_without(sentences, words, run)), schema)


ORACLE = r"""
with tiles as (
  select doc_id, unnest(t) as tile, generate_subscripts(t, 1) as pos
  from (select doc_id, regexp_extract_all(coalesce(text, ''), '[^.!?\n]*[.!?\n]+|[^.!?\n]+') as t from documents)
), worded as (
  select doc_id, tile, pos,
         regexp_extract_all(translate(tile, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') as w
  from tiles
), sentences as (
  select doc_id, pos, array_to_string(w, ' ') as norm, len(w) as n,
         row_number() over (partition by doc_id order by pos) as i,
         sum(len(w)) over (partition by doc_id order by pos) as upto
  from worded where len(w) > 0
), spans as (
  select doc_id, i, i as e, 'one ' || norm as span from sentences where n >= 20
  union all
  select a.doc_id, a.i, b.i, 'two ' || a.norm || chr(1) || b.norm from sentences a join sentences b on a.doc_id = b.doc_id and b.i = a.i + 1
), ranked as (
  select doc_id, i, e, row_number() over (partition by span order by doc_id, i) as nth from spans
), covered as (
  select distinct s.doc_id, s.pos, s.i, s.n from ranked r join sentences s on s.doc_id = r.doc_id and s.i in (r.i, r.e) where r.nth > 1
), stretches as (
  select *, i - row_number() over (partition by doc_id order by i) as stretch from covered
), gone as (
  select doc_id, pos from (select *, sum(n) over (partition by doc_id, stretch) as total from stretches) where total >= 20
), left_over as (
  select t.doc_id, string_agg(t.tile, '' order by t.pos) as text
  from tiles t left join gone g on g.doc_id = t.doc_id and g.pos = t.pos
  where g.pos is null group by t.doc_id
)
select d.doc_id,
       case when d.text is null then null else coalesce(l.text, '') end as text,
       coalesce(c.n, 0)::bigint as n_sentences,
       coalesce(g.n, 0)::bigint as n_removed
from documents d
left join left_over l on l.doc_id = d.doc_id
left join (select doc_id, count(*) as n from sentences group by doc_id) c on c.doc_id = d.doc_id
left join (select doc_id, count(*) as n from gone group by doc_id) g on g.doc_id = d.doc_id
"""

"""Near-duplicate documents by bottom-k sketches from one hash function.

1. A document becomes the set of hashes of its distinct word shingles; its
   sketch is the k smallest of them. Documents with equal sets form a class,
   and only one document of a class goes on.
2. Inverted lists of retained values give candidates. Two sets above the
   similarity share at least ``T`` retained values (but for a chance below
   ``LOST`` at the very border of similarity). Each class meets others first in
   the lists of its two least values; what hangs together there is one label.
3. Each class posts all but its ``T - 1`` most frequent values. A posting stays
   only while its list holds another label whose sets are of fitting size. A
   list that is long without its largest label is split by a second value; the
   largest label is dealt out in parts, each with all the others.
4. Inside a list a pair passes when the k smallest values of the union of both
   sketches hold at least ``T`` common ones, the estimate of their similarity.
   Lists emit a spanning set of the passing pairs, never all of them.
5. Those pairs are held against each other with their whole sets. Only where
   one fails, the labels on its two sides meet again with all their members,
   dealt out in the same way: there every passing pair of different labels is
   compared, until the labels are one.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nudgegraph.llm.text import need, shingle_set, trimmed, words_of
from nudgegraph.operators.components import components
from nudgegraph.session import Scratch

LOST = 1e-8
#: what a document weighs in a block besides its shingles: 512 documents fill one
ROW = 8192


def least_overlap(k: int, num: int, den: int) -> int:
    """Retained values that two sets at the similarity share, but for LOST."""
    p, tail = num / den, 0.0
    for t in range(k + 1):
        tail += math.comb(k, t) * p**t * (1 - p) ** (k - t)
        if tail > LOST:
            return max(1, t)
    return k


def _sets(width: int, k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            size, digest, sketch = [], [], []
            for text in batch.column(1):
                s = shingle_set(words_of(text.as_py()), width)
                size.append(len(s))
                digest.append(hashlib.blake2b(s.tobytes(), digest_size=16).digest())
                sketch.append(s[:k].view(np.int64))
            lists = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, sketch)]), pa.int32()), pa.array(np.concatenate([np.empty(0, np.int64), *sketch])))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(size, pa.int64()), pa.array(digest, pa.binary()), lists], ["doc_id", "n_shingles", "digest", "sketch"])

    return run


class _Forest:
    """Union-find whose roots know their members."""

    def __init__(self):
        self.up, self.members = [], {}

    def add(self) -> int:
        self.up.append(i := len(self.up))
        self.members[i] = [i]
        return i

    def root(self, i: int) -> int:
        while self.up[i] != i:
            self.up[i] = i = self.up[self.up[i]]
        return i

    def join(self, i: int, j: int) -> None:
        i, j = self.root(i), self.root(j)
        if i != j:
            if len(self.members[i]) < len(self.members[j]):
                i, j = j, i
            self.up[j] = i
            self.members[i] += self.members.pop(j)


def _grouped(batches: Iterator[pa.RecordBatch], n_keys: int) -> Iterator[tuple[tuple, list[tuple]]]:
    """Runs of rows with equal first columns, over batch borders."""
    key, rows = None, []
    for batch in batches:
        for row in zip(*[c.to_pylist() for c in batch.columns], strict=True):
            if row[:n_keys] != key:
                if rows:
                    yield key, rows
                key, rows = row[:n_keys], []
            rows.append(row[n_keys:])
    if rows:
        yield key, rows


def _passing(k: int, t: int, num: int, den: int):
    """Test of two (least, values) sketches by the k smallest values of their union.

    Values are cut to 31 bits, which keeps their order; ``least`` has been
    lowered where two values of one sketch fall together.
    """

    def passes(a: tuple[int, set], b: tuple[int, set]) -> bool:
        both = a[1] & b[1]
        if len(both) < min(max(a[0], b[0]), len(a[1]), len(b[1])):
            return False
        union = a[1] | b[1]
        if len(union) <= k:
            return True
        edge = sorted(union)[k - 1]
        return sum(v <= edge for v in both) >= min(t, max(a[0], b[0]))

    return passes


def _first_links(passes, front: int = 8):
    """Of each inverted list: a link from a document to one it passes with.

    Each is held against the ``front`` documents that others passed with last,
    so a list of any length costs its length. What this misses, the full lists
    find later.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        left, right, bucket, tops = [], [], None, []
        for batch in batches:
            for key, node, _, least, sketch in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                if key != bucket:
                    bucket, tops = key, []
                mine = set(sketch)
                own = (least - len(sketch) + len(mine), mine)
                for i, (other, theirs) in enumerate(tops):
                    if passes(own, theirs):
                        if other != node:
                            left.append(other)
                            right.append(node)
                        tops.insert(0, tops.pop(i))
                        break
                else:
                    tops.insert(len(tops) // 2, (node, own))
                    del tops[front:]
            yield pa.RecordBatch.from_arrays([pa.array(left, pa.int64()), pa.array(right, pa.int64())], ["a", "b"])
            left, right = [], []

    return run


def _spanning(passes):
    """Of each inverted list: pairs that pass, enough to connect what they connect.

    Nodes of one label are connected already.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        left, right = [], []

        def out():
            return pa.RecordBatch.from_arrays([pa.array(left, pa.int64()), pa.array(right, pa.int64())], ["a", "b"])

        for _, rows in _grouped(batches, 1):
            if len(rows) < 2:
                continue
            forest, seen, labels = _Forest(), [], {}
            for node, label, least, sketch in rows:
                mine, x = set(sketch), forest.add()
                own = (least - len(sketch) + len(mine), mine)
                if label in labels:
                    forest.join(x, labels[label])
                else:
                    labels[label] = x
                for r in list(forest.members):
                    if r not in forest.members or r == forest.root(x):
                        continue
                    for y in forest.members[r]:
                        other, theirs = seen[y]
                        if passes(own, theirs):
                            if other != node:
                                left.append(other)
                                right.append(node)
                            forest.join(x, y)
                            break
                seen.append((node, own))
            if len(left) > 50_000:
                yield out()
                left, right = [], []
        yield out()

    return run


def _alike(a: np.ndarray, b: np.ndarray, num: int, den: int) -> bool:
    """Whether two sorted sets are at the similarity, exactly."""
    if len(a) < len(b):
        a, b = b, a
    if not len(b) or len(b) * den < len(a) * num:
        return False
    at = np.searchsorted(a, b)
    at[at == len(a)] = 0
    both = int((a[at] == b).sum())
    return both * den >= (len(a) + len(b) - both) * num


def _placed_sets(batches: Iterator[pa.RecordBatch], width: int) -> Iterator[tuple[int, Iterator[tuple]]]:
    """(place, its (node, mark, set)s in order); rows of other texts than the class's and repeats of it are passed over."""
    from itertools import groupby

    def rows():
        for batch in batches:
            for i in range(batch.num_rows):
                yield tuple(c[i] for c in batch.columns)

    def some(group):
        last = None
        for _, mark, node, digest, text in group:
            node, mark = node.as_py(), mark.as_py()
            if node == last:
                continue
            s = shingle_set(words_of(text.as_py()), width)
            if hashlib.blake2b(s.tobytes(), digest_size=16).digest() == digest.as_py():
                last = node
                yield node, mark, s

    for place, group in groupby(rows(), key=lambda r: r[0].as_py()):
        yield place, some(group)


def _verified(width: int, num: int, den: int):
    """Of each place: its hub (mark 0) against every other, on whole sets."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a, b, ok = [], [], []

        def out():
            return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(ok, pa.bool_())], ["a", "b", "ok"])

        for _, sets in _placed_sets(batches, width):
            hub, its = None, None
            for node, mark, s in sets:
                if not mark:
                    hub, its = node, s
                else:
                    a.append(hub)
                    b.append(node)
                    ok.append(_alike(its, s, num, den))
            if len(a) > 50_000:
                yield out()
                a, b, ok = [], [], []
        yield out()

    return run


def _compared(width: int, k: int, t: int, num: int, den: int):
    """Of each place: links of labels, from all pairs of different labels until they are one."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, rows in _placed_sets(batches, width):
            forest, sets, labels, names, left, right = _Forest(), [], {}, [], [], []
            for _, label, s in rows:
                x, sk = forest.add(), set(s[:k].tolist())
                least = min(t, -(-len(s) * num // den))
                names.append(label)
                if label in labels:
                    forest.join(x, labels[label])
                else:
                    labels[label] = x
                for r in list(forest.members):
                    if r not in forest.members or forest.root(x) == r:
                        continue
                    mem = forest.members[r]
                    for i, y in enumerate(mem):
                        if len(sk & sets[y][0]) >= least and _alike(s, sets[y][1], num, den):
                            # what many are alike to is asked first from now on
                            mem[0], mem[i] = mem[i], mem[0]
                            left.append(names[y])
                            right.append(label)
                            forest.join(x, y)
                            break
                sets.append((sk, s))
            yield pa.RecordBatch.from_arrays([pa.array(left, pa.int64()), pa.array(right, pa.int64())], ["a", "b"])

    return run


def _fitting(posts: DataFrame) -> DataFrame:
    """The rows of ``posts`` whose list holds another label with sets of the same band or the next.

    A band of sizes is as wide as the similarity allows two sets to differ.
    """
    bands = posts.groupBy("value", "band").agg(F.min("label").alias("lo"), F.max("label").alias("hi"))
    lists = bands.groupBy("value").agg(F.collect_list(F.struct("band", "lo", "hi")).alias("bands"), F.min("lo").alias("lo"), F.max("hi").alias("hi"))
    lists = lists.where("lo < hi").select(F.col("value").alias("of"), "bands")
    fits = F.expr("value = of and exists(bands, b -> abs(b.band - band) <= 1 and (b.lo <> label or b.hi <> label))")
    return posts.join(lists, fits).drop("of", "bands")


def _by_key(rows: DataFrame, key: str) -> DataFrame:
    """Dealt by the key to a stated number of tasks: small ones aren't merged by their bytes, which say little of the work."""
    return rows.repartition(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), key)


def _dealt(rows: DataFrame, most: int) -> DataFrame:
    """(bucket, node, label): rows (value, node, label, w) of each value dealt out so that all of different labels meet.

    The value's heaviest label lies in blocks of about ``most``, and so do its
    others together. A block of the heaviest meets each block of the others, and
    those each other; nothing else is copied. Values of one label go.
    """
    weight = rows.groupBy("value", "label").agg(F.sum("w").alias("w"))
    weight = weight.groupBy("value").agg(F.max_by("label", F.struct("w", "label")).alias("big"), F.max("w").alias("top"), F.sum("w").alias("w"), F.count("*").alias("n")).where("n > 1")
    parts = F.when(F.col("w") <= most, 1)
    weight = weight.select(F.col("value").alias("of"), "big", parts.otherwise(F.ceil(F.col("top") / most)).alias("g"), parts.otherwise(F.ceil((F.col("w") - F.col("top")) / most)).alias("r"))
    met = rows.join(weight, F.col("value") == F.col("of")).withColumn("is_big", F.expr("label = big"))
    met = met.withColumn("i", F.pmod(F.xxhash64("node"), F.when(F.col("is_big"), F.col("g")).otherwise(F.col("r"))))
    spots = F.expr(
        "if(is_big, transform(sequence(0L, r - 1), j -> xxhash64(value, 0, i, j)),"
        " concat(transform(sequence(0L, g - 1), j -> xxhash64(value, 0, j, i)), if(r > 1, transform(sequence(0L, r - 1), j -> xxhash64(value, 1, least(i, j), greatest(i, j))), array())))"
    )
    return met.select(F.explode(spots).alias("bucket"), "node", "label")


def _candidates(shared: DataFrame, scratch: Scratch, passes, long_list: int) -> DataFrame:
    """(a, b): of the classes in ``shared`` a spanning set of the pairs that pass."""
    sketches = shared.select("node", "least", "sketch")

    def spanning(lists: DataFrame, how) -> DataFrame:
        lists = lists.join(sketches, "node").select("bucket", "node", "label", "least", "sketch")
        return _by_key(lists, "bucket").sortWithinPartitions("bucket", "node").mapInArrow(trimmed(how(passes)), "a long, b long")

    def dealt(n, of="node"):
        return F.pmod(F.xxhash64(of), F.ceil(n / long_list))

    # first the lists of the two least shared values, in parts: most copies meet there, however many they are
    least_two = F.slice(F.array_sort(F.transform("values", lambda x: F.struct(x["value"].alias("value"), x["often"].alias("often")))), 1, 2)
    two = shared.select("node", F.explode(least_two).alias("v")).select("node", F.col("node").alias("label"), "v.often", "v.value")
    first = scratch.keep(spanning(two.withColumn("bucket", F.xxhash64("value", dealt(F.col("often")))), _first_links), "first")
    early = scratch.keep(components(first).withColumnRenamed("component", "label"), "early")
    in_parts = two.where(F.col("often") > long_list)
    if not in_parts.isEmpty():  # then one of each label in a list whose parts were apart
        left = in_parts.drop("label").join(early, "node", "left").select("value", F.coalesce("label", "node").alias("label"))
        left = left.groupBy("value", "label").agg(F.count("*").alias("n"))
        left = left.select("value", "label", F.col("label").alias("node"))
        many = left.groupBy("value").agg(F.count("*").alias("often")).where("often > 1")
        again = spanning(left.join(many, "value").withColumn("bucket", F.xxhash64("value", dealt(F.col("often")))), _first_links)
        again = scratch.keep(again, "again")
        over = components(again).select(F.col("node").alias("label"), "component")
        early = scratch.keep(early.join(over, "label", "left").select("node", F.coalesce("component", "label").alias("label")).unionByName(
            over.select(F.col("label").alias("node"), F.col("component").alias("label")).join(early, "node", "left_anti")), "earlier")
        first = first.unionByName(again)

    # then all lists in which something isn't connected yet
    able = shared.join(early, "node", "left").select("node", F.coalesce("label", "node").alias("label"), "band", "least", "values")
    lists = able.select("node", "label", "band", F.explode(F.expr("slice(values, 1, size(values) - least + 1)")).alias("v"))
    lists = scratch.keep(_fitting(lists.select("node", "label", "band", "v.value")), "lists")
    sizes = lists.groupBy("value", "label").agg(F.count("*").alias("n")).groupBy("value").agg((F.sum("n") - F.max("n")).alias("others")).where(F.col("others") > long_list)
    wide = lists.join(sizes, "value").join(shared.select("node", "least", "values"), "node").withColumn("rest", F.expr("filter(values, x -> x.value <> value)"))
    wide = wide.withColumn("w", F.explode(F.expr("slice(rest, 1, greatest(0, size(rest) - least + 2))"))).select("node", "label", "band", F.xxhash64("value", "w.value").alias("value"))
    lists = lists.join(sizes, "value", "left_anti").select("value", "node", "label").unionByName(_fitting(wide).select("value", "node", "label"))
    late = spanning(_dealt(lists.withColumn("w", F.lit(1)), long_list), _spanning)
    return first.unionByName(late)


def _open_groups(labels: DataFrame, open_: DataFrame, classes: DataFrame, block: int) -> DataFrame:
    """(place, mark, node): members of the labels in ``open_`` where they meet those of other labels; ``mark`` is the label."""
    groups = open_.select(F.col("node").alias("label"), F.col("component").alias("value"))
    alone = groups.join(labels.select(F.col("node").alias("label")), "label", "left_anti").select(F.col("label").alias("node"), "label", "value")
    members = labels.join(groups, "label").select("node", "label", "value").unionByName(alone)
    members = members.join(classes.select("node", (F.col("n") + ROW).alias("w")), "node")
    return _dealt(members, block).select(F.col("bucket").alias("place"), F.col("label").alias("mark"), "node")


def near_duplicates(
    docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", shingle: int = 5, num: int = 80, den: int = 100, k: int = 64, long_list: int = 1024, block: int = 1 << 22, hub: int = 256
) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for every row of ``docs``.

    Two documents are linked when ``den * |A & B| >= num * |A | B|`` over their
    sets of ``shingle``-word shingles; a component is what links connect, its
    id the smallest ``doc_id``, and the row with that id is kept. A task holds
    a list or a part of it (``long_list`` rows), two blocks of ``block``
    shingles, or ``hub`` texts one after the other; any number of those come.

    Null or empty texts, and texts of white space, have an empty set and are
    linked with nothing. Fewer words than ``shingle`` make one shingle. Rows
    that repeat a ``doc_id`` are judged each by its own text. A null ``doc_id``
    is linked with nothing, gets a null ``component_id`` and is kept. Other
    columns are ignored. Empty tables give an empty result.
    """
    if not 2 * num > den:
        raise ValueError("the similarity must be over one half")
    t = least_overlap(k, num, den)
    scratch = Scratch(docs.sparkSession, "neardup")
    own = need(docs, id_col, text_col).toDF("doc_id", "text")
    info = scratch.keep(own.mapInArrow(trimmed(_sets(shingle, k)), "doc_id long, n_shingles long, digest binary, sketch array<bigint>"), "sets")
    some = info.where("doc_id is not null and n_shingles > 0")
    classes = some.groupBy("digest").agg(F.min("doc_id").alias("low"), F.first("n_shingles").alias("n"), F.first("sketch").alias("sketch"))
    # a class has a number of its own: rows of one doc_id may have different texts
    classes = scratch.keep(classes.withColumn("node", F.monotonically_increasing_id()), "classes")

    linked = None
    if num < den:
        smallest = -(-num // (den - num))  # sets below this size are like none but their equals
        least = F.least(F.lit(t), F.ceil(F.col("n") * num / den)).cast("int")
        band = F.floor(F.log("n") / (math.log(den / num) * (1 + 1e-9))).cast("int")
        able = classes.where(F.col("n") >= smallest)
        posts = able.select("node", F.explode("sketch").alias("value"))
        often = posts.groupBy("value").agg(F.count("*").alias("often")).where("often > 1")
        values = posts.join(often, "value").groupBy("node").agg(F.array_sort(F.collect_list(F.struct("often", "value"))).alias("values"))
        short = F.transform("sketch", lambda x: F.shiftrightunsigned(x, 33).cast("int"))
        able = able.select("node", least.alias("least"), band.alias("band"), short.alias("sketch"))
        shared = scratch.keep(able.join(values, "node").where(F.size("values") >= F.col("least")), "shared")
        pairs = scratch.keep(_candidates(shared, scratch, _passing(k, t, num, den), long_list).distinct(), "pairs")

        def with_texts(rows: DataFrame) -> DataFrame:
            rows = rows.join(classes.select("node", "low", "digest"), "node")
            rows = rows.join(own, F.col("low") == F.col("doc_id")).select("place", "mark", "node", "digest", "text")
            return _by_key(rows, "place").sortWithinPartitions("place", "mark", "node")

        hubs = pairs.join(pairs.groupBy("a").agg(F.ceil(F.count("*") / hub).alias("parts")), "a")
        hubs = hubs.select("a", "b", F.xxhash64("a", F.pmod(F.xxhash64("b"), "parts")).alias("place"))
        rows = hubs.select("place", F.lit(1).alias("mark"), F.col("b").alias("node")).unionByName(hubs.select("place", F.lit(0).alias("mark"), F.col("a").alias("node")).distinct())
        judged = scratch.keep(with_texts(rows).mapInArrow(trimmed(_verified(shingle, num, den)), "a long, b long, ok boolean"), "judged")
        labels = scratch.keep(components(judged.where("ok")).withColumnRenamed("component", "label"), "labels")
        side = lambda c: labels.select(F.col("node").alias(c), F.col("label").alias(f"of_{c}"))
        failed = judged.where("not ok").join(side("a"), "a", "left").join(side("b"), "b", "left")
        open_ = components(failed.select(F.coalesce("of_a", "a").alias("a"), F.coalesce("of_b", "b").alias("b")))
        places = _open_groups(labels, open_, classes, block)
        # written first: a stage of two Python steps would leave each task's second worker with the executor
        met = scratch.keep(with_texts(places).mapInArrow(trimmed(_compared(shingle, k, t, num, den)), "a long, b long"), "met")
        over = components(met)
        over = over.select(F.col("node").alias("label"), "component")
        joined = labels.join(over, "label", "left").select("node", F.coalesce("component", "label").alias("grp"))
        joined = joined.unionByName(over.join(labels.select(F.col("node").alias("label")), "label", "left_anti").select(F.col("label").alias("node"), F.col("component").alias("grp")))
        joined = scratch.keep(joined.join(classes.select("node", "low"), "node"), "joined")
        scratch.drop(*[df for df in scratch.frames() if df is not info and df is not classes and df is not joined])
        linked = joined.join(joined.groupBy("grp").agg(F.min("low").alias("class_id")), "grp").select("node", "class_id")

    names = classes.select("digest", "node", "low")
    if linked is not None:
        names = names.join(linked, "node", "left").select("digest", F.coalesce("class_id", "low").alias("class_id"))
    else:
        names = names.withColumnRenamed("low", "class_id")
    out = info.select("doc_id", "n_shingles", "digest").join(names.select(F.col("digest").alias("of"), "class_id"), (F.col("digest") == F.col("of")) & (F.col("n_shingles") > 0), "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("class_id", "doc_id"))
    return out.select("doc_id", "n_shingles", component.alias("component_id")).withColumn("kept", F.expr("doc_id <=> component_id"))


ORACLE = r"""
with recursive w as (
  select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') as w from documents
), s as materialized (
  select distinct doc_id, w[i] || case when len(w) > 1 then ' ' || w[i + 1] else '' end as s
  from (select doc_id, w, unnest(range(1, greatest(len(w), 2))) as i from w where len(w) > 0)
), n as materialized (select doc_id, count(*) as n from s group by doc_id),
both_ as (select a.doc_id as x, b.doc_id as y, count(*) as n from s a join s b on a.s = b.s and a.doc_id < b.doc_id group by a.doc_id, b.doc_id),
links as materialized (
  select b.x, b.y from both_ b join n p on p.doc_id = b.x join n q on q.doc_id = b.y where 100 * b.n >= 80 * (p.n + q.n - b.n)
), sides as materialized (select x as a, y as b from links union all select y, x from links),
reach as (select doc_id as d, doc_id as o from n union select sides.b, reach.o from reach join sides on sides.a = reach.d)
select w.doc_id, coalesce(n.n, 0)::bigint as n_shingles, coalesce(c.o, w.doc_id) as component_id, coalesce(c.o, w.doc_id) = w.doc_id as kept
from w left join n on n.doc_id = w.doc_id left join (select d, min(o) as o from reach group by d) c on c.d = w.doc_id
"""

import math
import random
import zlib
from collections import Counter

import numpy as np

from nudgegraph.llm.mixlm import ORDERS, grams, lm_scores, stream, train
from nudgegraph.llm.text import words_of


def base_of(rows):
    seen = Counter()
    for i, text in rows:
        if i is None or zlib.crc32(str(i).encode()) % 10:
            seen.update(words_of(text))
            seen[b""] += 1
    total, distinct = sum(seen.values()), len(seen)
    out = {}
    for i, text in rows:
        w = [*words_of(text), b""]
        out[i] = (len(w), sum(seen[x] > 0 for x in w), total, sum(math.log10((seen[x] + 0.1) / (total + 0.1 * (distinct + 1))) for x in w))
    return out


def test_base_against_counting(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    want = base_of([tuple(r) for r in docs.collect()])
    for frequent in (64, 1 << 17):
        for r in lm_scores(docs, frequent=frequent).collect():
            n, known, total, base = want[r.doc_id]
            assert (r.n_tokens, r.n_known, r.train_tokens) == (n, known, total) and abs(r.base_score - base) < 1e-6 * max(1, abs(base))
            assert r.score < 0 < r.bits_per_byte


def test_probabilities_sum_to_one(spark):
    model = train(spark.createDataFrame([("the cat sat on the mat",), ("the dog sat on the log",)], "text string")).scorer()
    for history in (b"\n\n\n\n\n", b"the c", b"zzzzz"):
        code = int.from_bytes(history[-ORDERS:], "big")
        p = 2 ** model.log2(np.array([(code << 8) | b for b in range(256)]))
        assert abs(p.sum() - 1) < 1e-3


def test_learned_text_is_likelier(spark):
    model = train(spark.createDataFrame([("the cat sat on the mat " * 20,)] * 5, "text string")).scorer()
    seen, other = model.log10_of([stream(b"the cat sat".split()), stream(b"qzx jkw vvy".split())])
    assert seen > other


def test_grams_see_own_text_only():
    codes = grams([b"ab\n", b"c\n"])
    assert len(codes) == 5 and codes[3] == int.from_bytes(b"\n" * ORDERS + b"c", "big")


def test_odd_rows(odd, none):
    out = {r.doc_id: r for r in lm_scores(odd).collect()}
    want = base_of([(r.doc_id, r.text) for r in odd.select("doc_id", "text").collect()])
    assert out[1].n_tokens == out[2].n_tokens == out[3].n_tokens == 1
    assert all(abs(out[i].base_score - want[i][3]) < 1e-6 * max(1, abs(want[i][3])) for i in out)
    assert lm_scores(none).count() == 0


def test_table_grows_with_the_corpus(spark):
    rng = random.Random(3)
    for size in (2_000, 200_000):
        model = train(spark.createDataFrame([("".join(rng.choices("abcdefghijklmnopqrstuvwxyz ", k=size)),)], "text string"))
        assert ((model.n0 + model.n1) > 0).mean() < 0.41


def test_scores_do_not_depend_on_partitions(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    found = []
    was = spark.conf.get("spark.sql.shuffle.partitions")
    try:
        for parts, some in ((2, docs), (16, docs.orderBy("text").repartition(5))):
            spark.conf.set("spark.sql.shuffle.partitions", str(parts))
            found.append({r.doc_id: r.score for r in lm_scores(some).collect()})
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", was)
    assert found[0] == found[1] and len(found[0]) == docs.count()


def test_shards_are_cut_in_steps(monkeypatch):
    import pyarrow as pa

    from nudgegraph.llm import mixlm

    monkeypatch.setattr(mixlm, "STEP", 3)
    shard = [0] * 7 + [2] * 2 + [5] * 4
    rows = [pa.RecordBatch.from_arrays([pa.array(shard[i : i + 4]), pa.array(list(range(i, min(i + 4, 13)))), pa.array([1] * len(shard[i : i + 4]))], ["shard", "gram", "n"]) for i in range(0, 13, 4)]
    got = [(s, [c.tolist() for c, _ in steps]) for s, steps in mixlm._shards(iter(rows))]
    assert got == [(0, [[0, 1, 2], [3, 4, 5], [6]]), (2, [[7, 8]]), (5, [[9, 10, 11], [12]])]


def plain_score(model, words):
    """log10 probability of a text, bit by bit, with plain numbers; counts looked up by slot."""
    from nudgegraph.llm.mixlm import _C1, _C2, _SEEN3, _SEEN4, STEPS

    total, history, size, mask = 0.0, b"\n" * ORDERS, len(model.n0), (1 << 64) - 1
    for byte in stream(words):
        prefix = 1
        for bit in range(7, -1, -1):
            x, seen = [], []
            for order in range(1, ORDERS + 1):
                context = ((int.from_bytes(history[-order:], "big") * 8 + order) & mask) * int(_C1) & mask
                node = (context ^ (prefix * int(_C2) & mask)) * int(_C2) & mask
                slot = ((node >> 33) * size) >> 31
                n0, n1 = float(model.n0[slot]), float(model.n1[slot])
                x.append(math.log((n1 + 0.05) / (n0 + 0.05)))
                seen.append(n0 + n1)
            gate = (sum(seen[-1] >= e for e in _SEEN4) * (len(_SEEN3) + 1) + sum(seen[-2] >= e for e in _SEEN3)) * 8 + bit
            w = model.weights[gate]
            m = min(12, max(-12, sum(a * b for a, b in zip(w, [*x, 0.3], strict=True))))
            step = round((min(8, max(-8, m)) + 8) * STEPS / 16)
            p = (1 / (1 + math.exp(-m)) + model.refine[gate * (STEPS + 1) + step]) / 2
            p = min(1 - 1e-6, max(1e-6, p))
            y = byte >> bit & 1
            total += math.log10(p if y else 1 - p)
            prefix = prefix << 1 | y
        history = history[1:] + bytes([byte])
    return total


def test_scores_against_plain_arithmetic(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").where("length(text) < 400").limit(40).cache()
    rows = [tuple(r) for r in docs.collect()]
    model = train(docs.where("crc32(cast(cast(doc_id as string) as binary)) % 10 <> 0"))
    for r in lm_scores(docs).collect():
        want = plain_score(model, words_of(dict(rows)[r.doc_id]))
        assert abs(r.score - want) < 1e-3 * max(1, abs(want)), (r, want)


def test_counts_against_plain_counting(spark):
    """Every bit of the training texts is counted once in each order's node; no other slot is filled."""
    texts = ["ab ba", "ab", "", "c ab"]
    model = train(spark.createDataFrame([(t,) for t in texts], "text string"))
    n_bytes = sum(len(stream(words_of(t))) for t in texts)
    assert (model.n0 + model.n1).sum() == 8 * ORDERS * n_bytes
    ones = sum(bin(b).count("1") for t in texts for b in stream(words_of(t)))
    assert model.n1.sum() == ORDERS * ones


def test_counting_lets_go_of_the_last_table():
    """A worker that counts for a new run doesn't keep the table of the run before."""
    from nudgegraph.llm import mixlm

    for kernel in (mixlm._counted_words, mixlm._counted_grams, mixlm._node_counts):
        mixlm._HELD["gone", True] = np.zeros(1, np.float32), np.zeros(1, np.uint8)
        assert list(mixlm._counting(kernel)(iter(()))) == [] and not mixlm._HELD


def test_a_slot_takes_eight_bytes_to_learn(spark):
    model = train(spark.createDataFrame([("the cat sat on the mat",)], "text string"))
    assert model.n0.itemsize + model.n1.itemsize == 8

import math
import zlib
from collections import Counter

from nudgegraph.llm.langid import identify, learn, training_rows, trigrams


def test_held_out_accuracy(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    model = learn(training_rows(docs))
    out = identify(docs, model).join(docs.select("doc_id", "lang"), "doc_id").where("held_out and lang is not null and lang_pred <> 'und'")
    assert out.where("lang = lang_pred").count() >= 0.97 * out.count() > 0


def test_training_leaves_out(spark):
    ids = spark.range(200).selectExpr("id as doc_id")
    kept = {r.doc_id for r in training_rows(ids).collect()}
    assert kept == {i for i in range(200) if zlib.crc32(str(i).encode()) % 4 != 2}


def test_mixture(spark):
    a, b = "lorem ipsum dolor sit amet " * 20, "zwölf größe über straße weiß " * 20
    rows = [(i, a, "x") for i in range(5)] + [(i + 5, b, "y") for i in range(5)]
    model = learn(spark.createDataFrame(rows, "doc_id long, text string, lang string"))
    one, two = model.predict(a), model.predict(a + b)
    assert one[0] == "x" and list(one[2]) == ["x"] and set(two[2]) == {"x", "y"} and abs(sum(two[2].values()) - 1) < 1e-6


def test_odd_rows(odd, none):
    out = {r.doc_id: r for r in identify(odd, learn(odd)).collect()}
    assert all(out[i].lang_pred == "und" and out[i].score == 0 for i in (1, 2, 3, 5)) and all(0 <= r.score <= 1 for r in out.values())
    assert identify(none, learn(none)).count() == 0 and identify(odd, learn(none)).where("lang_pred <> 'und'").count() == 0


def plain_mixture(tables, text):
    """Shares by expectation maximisation and the penalised choice, in plain Python on dictionaries."""
    seen = Counter(int(g) for g in trigrams(text))
    total, langs = sum(seen.values()), sorted(tables)
    p = {x: {g: (tables[x][g] + 0.5) / (sum(tables[x].values()) + 0.5 * 65536) for g in seen} for x in langs}
    loglik = lambda share: sum(c * math.log(sum(share[x] * p[x][g] for x in share)) for g, c in seen.items())

    def fit(share, rounds):
        for _ in range(rounds):
            new = dict.fromkeys(share, 0.0)
            for g, c in seen.items():
                whole = sum(share[x] * p[x][g] for x in share)
                for x in share:
                    new[x] += c * share[x] * p[x][g] / whole / total
            done = max(abs(new[x] - share[x]) for x in share) < 1e-4
            share = new
            if done:
                break
        return share

    alone = {x: loglik({x: 1.0}) for x in langs}
    first = max(langs, key=lambda x: (alone[x], [-ord(c) for c in x]))
    best, value = {first: 1 / sum(math.exp(max(alone[x] - alone[first], -700)) for x in langs)}, alone[first]
    full = fit(dict.fromkeys(langs, 1 / len(langs)), 20)
    order = sorted(langs, key=lambda x: -full[x])
    for m in range(2, max(2, sum(full[x] >= 1e-3 for x in langs)) + 1):
        start = {x: max(full[x], 1e-6) for x in order[:m]}
        share = fit({x: v / sum(start.values()) for x, v in start.items()}, 15)
        worth = loglik(share) - 2 * math.log(total) * (m - 1)
        if worth > value:
            best, value = share, worth
    return best


def test_against_plain_python(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    model = learn(training_rows(docs))
    tables = {}
    for r in training_rows(docs).where("lang is not null and text is not null").select("lang", "text").collect():
        grams = trigrams(r.text)
        if grams is not None:
            tables.setdefault(r.lang, Counter()).update(int(g) for g in grams)
    rows = [r.text[:1500] for r in docs.where("length(text) > 300").orderBy("doc_id").limit(24).collect()]
    texts = rows + [a + " " + b for a, b in zip(rows[::2], rows[1::2], strict=True)]
    out = identify(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), model)
    mixed = 0
    for r in out.collect():
        want = plain_mixture(tables, texts[r.doc_id])
        assert set(r.mixture) == set(want) and all(abs(r.mixture[x] - want[x]) < 1e-3 for x in want), (r, want)
        assert r.lang_pred == max(want, key=want.get) and abs(r.score - min(1.0, max(want.values()))) < 1e-3
        mixed += len(want) > 1
    assert mixed

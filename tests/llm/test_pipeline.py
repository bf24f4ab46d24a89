import corpus_pipeline as cp
from test_neardup import brute

from nudgegraph.llm import decontaminate as d


def test_stages_against_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    stages = dict(cp.STAGES)
    kept = stages["language_id"](spark, docs, sf)
    assert kept.columns == cp.COLUMNS and kept.count() >= 0.98 * docs.where("text rlike '[A-Za-z]'").count()
    rows = [(r.doc_id, r.text) for r in kept.collect()]
    one = stages["near_dedup"](spark, kept, sf)
    assert sorted(r.doc_id for r in one.collect()) == sorted(i for i, _, c in brute(rows, 5, 80, 100) if i == c)
    cut = stages["repeats"](spark, one, sf)
    assert cut.columns == cp.COLUMNS and cut.where("n_chars <> length(text)").count() == 0
    clean = stages["decontamination"](spark, cut, sf)
    items = [(r.item_id, d.plain_words(r.text)) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    windows = {tuple(w[i : i + min(10, len(w))]) for _, w in items for i in range(max(1, len(w) - 9)) if w}
    sizes = {len(w) for w in windows}
    dirty = {r.doc_id for r in cut.collect() if any(tuple(w[i : i + n]) in windows for w in [d.plain_words(r.text)] for n in sizes for i in range(len(w) - n + 1))}
    assert {r.doc_id for r in clean.collect()} == {r.doc_id for r in cut.collect()} - dirty
    coded = stages["encoding"](spark, clean, sf)
    assert coded.count() == clean.count() and cp.run(spark, sf).count() == coded.count()


def test_odd_rows(spark, odd, none, sf):
    for docs in (none, odd.select(*cp.COLUMNS)):
        for _, stage in cp.STAGES:
            docs = stage(spark, docs, sf)
        docs.collect()

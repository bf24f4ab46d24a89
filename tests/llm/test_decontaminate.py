from helpers import same_rows
from hypothesis import given, settings
from hypothesis import strategies as st

from nudgegraph.llm import decontaminate as d


def test_sql_twin(spark, sf, duck):
    docs, items = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "benchmark"))
    same_rows(d.decontaminate(docs, items), duck.sql(d.ORACLE))
    # many shards give the same
    same_rows(d.decontaminate(docs, items, shard_bytes=4000), duck.sql(d.ORACLE))


@settings(max_examples=200, deadline=None)
@given(st.lists(st.sampled_from("abc"), max_size=40), st.lists(st.lists(st.sampled_from("abc"), max_size=7), max_size=5), st.integers(1, 4))
def test_search_against_scanning(words, items, window):
    search = d.PatternSearch([(str(i), " ".join(t)) for i, t in enumerate(items)], window)
    spans, owners = [], set()
    w = [x.encode() for x in words]
    search.find(w, spans, owners)
    want, who = set(), set()
    for i, t in enumerate(items):
        n = min(window, len(t))
        for s in range(len(t) - n + 1 if t else 0):
            for at in range(len(words) - n + 1):
                if words[at : at + n] == t[s : s + n]:
                    want.add((at, at + n))
                    who.add(str(i))
    assert set(spans) == want and {search.names[i] for i in owners} == who


def test_odd_rows(spark, odd, none):
    items = spark.createDataFrame([(1, "One two three."), (2, None), (None, "word word"), (3, "")], "item_id long, text string")
    by = {r.doc_id: r for r in d.decontaminate(odd, items).collect()}
    assert by[4].contaminated and by[4].n_hit == 3 and by[4].n_items == 1 and not by[6].contaminated and by[1].n_words == 0
    assert d.decontaminate(none, items).count() == 0 and d.decontaminate(odd, items.limit(0)).where("contaminated").count() == 0

import datetime as dt

from helpers import same_rows

from nudgegraph.llm import preferences as pf
from nudgegraph.llm import queries, urlfilter


def test_sql_twins(spark, sf, duck):
    for name in ("op6_dated_url_lists", "op7_preference_pairs"):
        same_rows(queries.QUERIES[name](spark, sf), duck.sql(queries.ORACLES[name]))


def test_dated_entries(spark):
    day = lambda n: dt.date(2024, 1, n)
    entries = spark.createDataFrame([("bad.com", True, day(5), 0, True), ("bad.com", True, day(9), 0, False), ("a.b.org", False, day(1), 0, True), ("a.b.org", False, day(1), 1, False), (None, True, day(1), 0, True)], "pattern string, wide boolean, day date, seq int, listed boolean")
    rows = [(1, "http://x.bad.com/p", day(4)), (2, "http://X.bad.com/p", day(5)), (3, "https://u@bad.com:8/", day(8)), (4, "http://bad.com", day(9)), (5, "http://notbad.com", day(6)), (6, None, day(6)), (7, "http://a.b.org", day(2)), (8, "http://bad.com", None), (None, "http://bad.com", day(6)), (2, "http://X.bad.com/p", day(5))]
    out = urlfilter.filter_urls(spark.createDataFrame(rows, "page_id long, url string, fetched date"), entries).collect()
    assert len(out) == len(rows) and sorted((r.page_id or 0) for r in out if r.blocked) == [0, 2, 2, 3]
    assert urlfilter.filter_urls(spark.createDataFrame([], "page_id long, url string, fetched date"), entries).count() == 0


def test_common_prefix(spark):
    turns = [(1, c, i, role, text) for c, texts in ((True, ["Hi", "Hello", "Bye"]), (False, ["Hi", "Hello", "No"])) for i, (role, text) in enumerate(zip(["user", "assistant", "assistant"], texts, strict=True))]
    turns += [(2, True, 0, "user", None), (2, True, 0, "user", None), (3, False, 0, None, "x"), (None, True, 0, "user", "lost")]
    out = {r.pair_id: r for r in pf.format_preferences(spark.createDataFrame(turns, "pair_id long, chosen boolean, turn long, role string, text string")).collect()}
    r = out[1]
    assert set(out) == {1, 2, 3} and r.n_common == 2 and r.prompt.count("<|im_start|>") == 2
    (span,) = r.chosen_mask
    assert r.chosen[span.start : span.end] == "Bye<|im_end|>\n" and r.rejected.startswith("<|im_start|>assistant\nNo")
    assert out[2].n_chosen == 2 and out[2].n_rejected == 0 and out[2].rejected == "" and out[3].rejected.startswith("<|im_start|>unknown")


def test_no_pairs(spark):
    assert pf.format_preferences(spark.createDataFrame([], "pair_id long, chosen boolean, turn long, role string, text string")).count() == 0

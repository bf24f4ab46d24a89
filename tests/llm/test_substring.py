import random

from helpers import same_rows

from nudgegraph.llm import substring
from nudgegraph.llm.text import words_of


def test_sql_twin(spark, sf, duck):
    same_rows(substring.substring_dedup(spark.read.parquet(f"{sf}/documents.parquet")), duck.sql(substring.ORACLE))


def test_repeated_passage(spark):
    passage = "Here is a passage of several sentences. It goes on for quite some words here. And then it ends with these words."
    rows = [(1, f"First own words. {passage} Mine alone is this."), (2, f"Quite other start.\n{passage} Nothing shared after."), (3, "Clean text. With its own words only.")]
    out = {r.doc_id: r for r in substring.substring_dedup(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert out[1].text == rows[0][1] and out[3].text == rows[2][1] and out[1].n_removed == 0
    assert out[2].text == "Quite other start.\n Nothing shared after." and out[2].n_removed == 3


def test_repeats_inside_a_document(spark):
    line = "Some words that make a line of text which repeats itself often.\n"
    out = substring.substring_dedup(spark.createDataFrame([(1, line * 6)], "doc_id long, text string")).first()
    assert 0 < out.n_removed < 6 and out.text.startswith(line)


def _words(prefix, n):
    return " ".join(f"{prefix}{i}" for i in range(n))


def test_rows_that_share_an_id_keep_what_is_theirs(spark):
    passage = f"{_words('a', 12)}. {_words('b', 12)}."
    rows = [(1, passage), (2, "Own opening. " + passage), (2, "One more text. That nobody else has. Not anywhere at all.")]
    out = sorted((r.doc_id, r.n_removed, r.text) for r in substring.substring_dedup(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert [(i, n) for i, n, _ in out] == [(1, 0), (2, 0), (2, 2)] and out[1][2] == rows[2][1] and out[2][2] == "Own opening."


def test_whole_passages_go(spark):
    """A short last sentence goes with its passage; so does one long sentence between others."""
    passage = f"{_words('a', 15)}. {_words('b', 15)}. {_words('c', 15)}. {_words('d', 3)}."
    long = f"{_words('e', 60)}."
    rows = [(1, f"First. {passage} Then this. {long} End here."), (2, f"Second start. {passage} Other words now."), (3, f"Third start. {long} Something else."), (4, "Yes. No. Other."), (5, "Yes. No. Different.")]
    out = {r.doc_id: r for r in substring.substring_dedup(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert out[2].n_removed == 4 and out[2].text == "Second start. Other words now." and out[3].n_removed == 1 and out[3].text == "Third start. Something else."
    assert out[1].n_removed == out[4].n_removed == out[5].n_removed == 0, "short stretches stay"


def brute(rows, words=20):
    """Spans as tuples, all occurrences listed, by definition."""
    import re

    texts = {i: [(t, tuple(t.lower().split())) for t in re.findall(substring.TILE, text)] for i, text in rows}
    sentences = {i: [(j, w) for j, (_, w) in enumerate(ts) if w] for i, ts in texts.items()}
    first, out = {}, {}
    for i in sorted(sentences):
        s = [w for _, w in sentences[i]]
        spans = [(j, j + 1) for j in range(len(s)) if len(s[j]) >= words] + [(j, j + 2) for j in range(len(s) - 1)]
        covered = [False] * len(s)
        for a, b in sorted(spans):
            if first.setdefault(tuple(s[a:b]), (i, a)) != (i, a):
                covered[a:b] = [True] * (b - a)
        at = 0
        gone = set()
        while at < len(s):
            end = at
            while end < len(s) and covered[end]:
                end += 1
            if sum(len(w) for w in s[at:end]) >= words:
                gone |= {sentences[i][j][0] for j in range(at, end)}
            at = max(end, at + 1)
        out[i] = "".join(t for j, (t, _) in enumerate(texts[i]) if j not in gone), len(gone)
    return out


def test_against_brute_force(spark):
    rng = random.Random(8)
    pool = [_words(f"s{i}_", rng.choice([1, 3, 8, 12, 25])) for i in range(14)]
    rows = [(i, "".join(rng.choice(pool) + rng.choice([". ", "! ", ".\n"]) for _ in range(rng.randrange(0, 9)))) for i in range(60)]
    out = {r.doc_id: (r.text, r.n_removed) for r in substring.substring_dedup(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert out == brute(rows)


def test_odd_rows(odd, none):
    out = substring.substring_dedup(odd)
    assert out.count() == odd.count()
    by = {r.doc_id: r for r in out.collect()}
    assert by[1].text is None and by[2].text == "" and by[3].text == " \n\t " and by[3].n_sentences == 0
    assert substring.substring_dedup(none).count() == 0


def _varied(rng, n):
    return " ".join("".join(rng.choices("abcdefghij", k=6)) for _ in range(n))


def test_runs_without_regard_to_sentences(spark):
    rng = random.Random(5)
    passage, cut = _varied(rng, 60), _varied(rng, 25) + ". " + _varied(rng, 35)
    rows = [
        (1, f"{_varied(rng, 30)}. {passage.capitalize()}. {_varied(rng, 9)}."), (2, f"{_varied(rng, 8)}.\n{passage}. {_varied(rng, 8)}."),
        (3, f"{_varied(rng, 12)} {cut} {_varied(rng, 12)}"), (4, f"{_varied(rng, 7)} {cut}\t{_varied(rng, 5)} {_varied(rng, 100)}"),
        (None, f"{_varied(rng, 3)} {passage} {_varied(rng, 3)}"), (5, f"{passage[: passage.index(' ', 330)]} {_varied(rng, 20)}"),
    ]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    out = {r.doc_id: r for r in substring.substring_dedup(docs, run=50).collect()}
    assert all(out[i].text == dict(rows)[i] and out[i].n_removed == 0 for i in (1, 3, 5)), "48 words or a first place stay"
    assert out[2].text == rows[1][1].replace(passage + ".", "") and out[2].n_removed == 1
    assert len(words_of(out[4].text)) == 7 + 5 + 100 and len(words_of(out[None].text)) == 3 + 3 + 1, "the last word of the passage has no full stop there"

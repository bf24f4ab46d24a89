import random

from hypothesis import given, settings
from hypothesis import strategies as st

from nudgegraph.llm import neardup
from nudgegraph.llm.neardup import least_overlap, near_duplicates
from nudgegraph.llm.text import shingle_set, words_of


def brute(rows, width, num, den):
    sets = []
    for _, text in rows:
        w = words_of(text)
        sets.append(frozenset(tuple(w[i : i + width]) for i in range(len(w) - width + 1)) if len(w) >= width else frozenset([tuple(w)] if w else []))
    up = list(range(len(rows)))

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if sets[i] and sets[j] and rows[i][0] is not None and rows[j][0] is not None and den * both >= num * len(sets[i] | sets[j]):
                up[root(i)] = root(j)
    groups = {}
    for i, (d, _) in enumerate(rows):
        if d is not None:
            groups.setdefault(root(i), []).append(d)
    return sorted((d, len(s), None if d is None else min(groups[root(i)])) for i, ((d, _), s) in enumerate(zip(rows, sets, strict=True)) if d is not None)


def got(df):
    return sorted((r.doc_id, r.n_shingles, r.component_id) for r in df.collect() if r.doc_id is not None)


def test_against_all_pairs(spark):
    rng = random.Random(5)
    vocabulary = ["the", "of", "and"] * 5 + [f"w{i}" for i in range(300)]
    rows, n = [], 0
    for _ in range(25):
        base = [rng.choice(vocabulary) for _ in range(rng.choice([3, 6, 20, 60, 120]))]
        for _ in range(rng.randrange(1, 8)):
            copy = list(base)
            for _ in range(rng.randrange(0, 1 + len(base) // 12)):
                copy[rng.randrange(len(copy))] = rng.choice(vocabulary)
            rows.append((n, " ".join(copy)))
            n += 1
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert got(near_duplicates(df, shingle=2)) == brute(rows, 2, 80, 100)
    # short lists and small blocks take the other ways to the same links
    assert got(near_duplicates(df, shingle=2, long_list=2, block=60, hub=2)) == brute(rows, 2, 80, 100)


def test_one_id_with_different_texts(spark):
    text = " ".join(f"w{i}" for i in range(30))
    rows = [(5, text), (5, "other words of the same number and no more"), (7, text + " end"), (9, "other words of the same number and no more")]
    out = near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), shingle=2).collect()
    assert sorted((r.doc_id, r.component_id, r.kept) for r in out) == [(5, 5, True), (5, 5, True), (7, 5, False), (9, 5, False)]


def test_pairs_at_the_border(spark):
    """Pairs whose similarity is 0.80 to 0.84: none may be missed."""
    rng, rows = random.Random(11), []
    for n in range(300):
        size = rng.randrange(25, 400)
        words = [f"{n}x{i}" for i in range(size + 1)]
        most = size // 9  # with one-word shingles m changed words leave (s - m) / (s + m)
        rows += [(2 * n, " ".join(words[:size])), (2 * n + 1, " ".join(words[: size - most] + [f"{n}y{i}" for i in range(most)]))]
    out = got(near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), shingle=1))
    assert [c for _, _, c in out] == [d // 2 * 2 for d, _, _ in out]


def test_odd_rows(odd):
    rows = near_duplicates(odd, shingle=2).collect()
    assert len(rows) == odd.count()
    by = {}
    for r in rows:
        by.setdefault(r.doc_id, r)
    assert by[1].n_shingles == by[2].n_shingles == by[3].n_shingles == 0 and by[2].kept and by[3].kept
    assert by[4].component_id == -9 and not by[4].kept and by[-9].kept
    assert by[None].component_id is None and by[None].kept
    assert by[6].n_shingles == 1 and by[7].n_shingles == 1


def test_empty(none):
    assert near_duplicates(none).count() == 0


def test_threshold_loses_less_than_stated():
    assert least_overlap(64, 80, 100) == 31


@settings(max_examples=50, deadline=None)
@given(st.lists(st.sampled_from([b"a", b"b", b"c"]), max_size=12), st.integers(1, 5))
def test_shingle_count(words, width):
    want = {tuple(words[i : i + width]) for i in range(len(words) - width + 1)} if len(words) >= width else ({tuple(words)} if words else set())
    assert len(shingle_set(words, width)) == len(want)


def test_sql_twin(spark, sf, duck):
    from helpers import same_rows

    from nudgegraph.llm import neardup

    same_rows(near_duplicates(spark.read.parquet(f"{sf}/documents.parquet"), shingle=2), duck.sql(neardup.ORACLE))


def test_no_stage_of_two_python_steps(spark, monkeypatch):
    """Components begin with a Python step, so what they get must be written already."""
    plans, components = [], neardup.components

    def seen(edges, *more):
        plans.append(edges._jdf.queryExecution().optimizedPlan().toString())
        return components(edges, *more)

    monkeypatch.setattr(neardup, "components", seen)
    rows = [(i, " ".join(f"w{j}" for j in range(30)) + f" end{i}") for i in range(5)]
    near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), shingle=2).collect()
    assert len(plans) >= 3 and not [p for p in plans if "MapInArrow" in p]


def test_workers_give_memory_back(monkeypatch):
    from nudgegraph.llm import text

    pool = []
    monkeypatch.setattr(text.pa, "default_memory_pool", lambda: type("Pool", (), {"release_unused": lambda _: pool.append(1)})())
    kernel = text.trimmed(lambda batches: (b + 1 for b in batches))
    assert list(kernel(iter([1, 2]))) == [2, 3] and pool == [1]

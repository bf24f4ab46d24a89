import math

import numpy as np
from helpers import same_rows

from nudgegraph.llm import neighbours as nb


def test_sql_twin(spark, sf, duck):
    v = spark.read.parquet(f"{sf}/embeddings.parquet")
    same_rows(nb.cosine_neighbours(v, v.where("vec_id % 50 = 0")), duck.sql(nb.ORACLE))


def test_many_shards_and_blocks(spark, sf, duck):
    v = spark.read.parquet(f"{sf}/embeddings.parquet")
    same_rows(nb.cosine_neighbours(v, v.where("vec_id % 50 = 0"), shard_rows=60, block=3, leaf=8), duck.sql(nb.ORACLE))


def test_relaxed_recall():
    rng = np.random.default_rng(3)
    centres = rng.normal(size=(30, 64))
    x = centres[rng.integers(0, 30, 4000)] + 0.3 * rng.normal(size=(4000, 64))
    x /= np.linalg.norm(x, axis=1)[:, None]
    tree = nb.build(x, 64)
    ids, order = np.arange(4000), tree["order"]
    exact = np.argsort(-(x[:80] @ x.T), axis=1, kind="stable")
    for factor, least in ((1.0, 1.0), (1.5, 0.9)):
        found = order[nb.Search(ids[order], x[order], tree["nodes"], 5, factor).run(ids[:80], x[:80])]
        recall = np.mean([len(set(f) & set(e[1:6])) / 5 for f, e in zip(found, exact, strict=True)])
        assert recall >= least


def test_odd_rows(spark):
    rows = [(0, [1.0, 0.0]), (50, [1.0, 0.0]), (3, [1.0, 0.0]), (2, [2.0, 0.0]), (4, None), (5, [0.0, 0.0]), (6, [math.nan, 1.0]), (7, [None, 1.0]), (8, [math.inf, 1.0]), (9, [0.0, 1.0]), (None, [1.0, 1.0]), (10, [1.0]), (11, [])]
    v = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    out = nb.cosine_neighbours(v, v.where("vec_id % 50 = 0")).orderBy("query_id", "rank").collect()
    assert [(r.query_id, r.vec_id, r.score) for r in out] == [(0, 2, 1.0), (0, 3, 1.0), (0, 50, 1.0), (0, 9, 0.0), (50, 0, 1.0), (50, 2, 1.0), (50, 3, 1.0), (50, 9, 0.0)]
    assert nb.cosine_neighbours(v.limit(0), v.limit(0)).count() == 0


def test_hot_vector(spark):
    rows = [(i, [1.0, 2.0, 3.0]) for i in range(600)] + [(i + 600, [float(i % 7), 1.0, float(i % 11)]) for i in range(300)]
    v = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    out = nb.cosine_neighbours(v, v.where("vec_id = 100"), shard_rows=200, leaf=16).orderBy("rank").collect()
    assert [r.vec_id for r in out] == [0, 1, 2, 3, 4]


def test_large_and_small_components(spark):
    rows = [(0, [1e200, 1e200]), (1, [1e200, 0.0]), (2, [1e-200, 1e-200]), (3, [1.0, 1.0]), (4, [-1e300, -1e-300])]
    v = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    out = {r.vec_id: r.score for r in nb.cosine_neighbours(v, v.where("vec_id = 0")).collect()}
    want = {1: math.sqrt(0.5), 2: 1.0, 3: 1.0, 4: -math.sqrt(0.5)}
    assert set(out) == set(want) and all(abs(out[i] - x) < 1e-12 for i, x in want.items())

import os
import shutil
import subprocess
import sys

import pytest
from helpers import same_rows

import __spark_entry__ as entry
from nudgegraph import catalogue

# slow ones are left to the driver's own comparison
SKIP = {n for n in catalogue.QUERIES if n.startswith(("exp_boost", "exp_random", "exp_beta", "exp_budget", "exp_compression", "exp_sandwich", "exp_seed", "influence_rank_conv", "strategies", "sketch_compression"))}


@pytest.mark.parametrize("name", sorted(n for n in catalogue.QUERIES if n in catalogue.ORACLES and n not in SKIP))
def test_sql_twin(spark, sf, duck, name):
    same_rows(catalogue.QUERIES[name](spark, sf), duck.sql(catalogue.ORACLES[name]))


def test_entry(spark):
    assert entry.entry(spark).columns == ["rank", "node", "gain"]


def test_without_the_subpackage(tmp_path):
    """Everything else imports when the training-data operators are gone."""
    root = os.path.dirname(os.path.abspath(entry.__file__))
    shutil.copytree(f"{root}/nudgegraph", tmp_path / "nudgegraph", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(f"{root}/__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; n = e.queries(); assert 'net_events_6h' in n and not any(x.startswith('op') for x in n), n; assert set(e.oracle_sql()) <= set(n)"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env=os.environ | {"PYTHONPATH": str(tmp_path)})


def test_scratch_tables_go(spark):
    from nudgegraph import session

    held = session.Scratch(spark, "test").keep(spark.range(3), "rows")
    path = held.inputFiles()[0].removeprefix("file://").rsplit("/", 1)[0]
    assert held.count() == 3 and os.path.isdir(path) and any(p.endswith(os.path.basename(path)) for p in session._KEPT)
    session.Scratch(spark, "test").drop(held)  # another one's table stays
    assert os.path.isdir(path)
    kept = dict(session._KEPT)
    session._KEPT.clear()
    session._KEPT.update({p: s for p, s in kept.items() if p.endswith(os.path.basename(path))})
    session.close()
    session._KEPT.update({p: s for p, s in kept.items() if not p.endswith(os.path.basename(path))})
    assert not os.path.isdir(path)


def test_small_and_large_graphs_have_the_same_components(spark, monkeypatch):
    from nudgegraph.operators import components as c

    edges = spark.createDataFrame([(i, (i * 7) % 90) for i in range(90)] + [(200 + i, 201 + i) for i in range(25)], "a long, b long")
    one = sorted(map(tuple, c.components(edges).collect()))
    monkeypatch.setattr(c, "ONE_TASK", 0)
    assert sorted(map(tuple, c.components(edges).collect())) == one

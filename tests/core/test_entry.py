"""Every query with SQL gives what the SQL gives."""

import math
import os
import subprocess
import sys

import duckdb
import pytest

from topicgrid.plans.queries import ORACLES, QUERIES

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return c


def plain(rows, names):
    at = sorted(range(len(names)), key=lambda k: names[k])
    norm = lambda v: None if v is None or v != v else float(f"{v:.9g}") if isinstance(v, float) else v
    return sorted((tuple(norm(r[k]) for k in at) for r in rows), key=str)


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query(spark, con, sf, name):
    df = QUERIES[name](spark, sf)
    want = con.sql(ORACLES[name])
    assert sorted(df.columns) == sorted(want.columns)
    a, b = plain(map(tuple, df.collect()), df.columns), plain(want.fetchall(), want.columns)
    assert len(a) == len(b)
    for x, y in zip(a, b, strict=True):
        assert all(u == v or (isinstance(u, float) and isinstance(v, float) and math.isclose(u, v, rel_tol=1e-8)) for u, v in zip(x, y, strict=True)), (x, y)


def test_imports_without_the_training_data_operators(tmp_path):
    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    for x in os.listdir(root):
        if x not in ("corpus_pipeline.py", "topicgrid", ".git"):
            os.symlink(f"{root}/{x}", tmp_path / x)
    (tmp_path / "topicgrid").mkdir()
    for x in os.listdir(f"{root}/topicgrid"):
        if x != "llm":
            os.symlink(f"{root}/topicgrid/{x}", tmp_path / "topicgrid" / x)
    code = "import __spark_entry__ as e; assert len(e.queries()) > 100 and not any(q.startswith('op') and q[2].isdigit() for q in e.queries()); assert set(e.oracle_sql()) <= set(e.queries())"
    env = {k: v for k, v in os.environ.items() if k != "PYTHONPATH"}
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env=env)

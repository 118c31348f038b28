"""The queries that SQL can express give what the SQL gives."""

import duckdb
import pytest

from topicgrid.llm.queries import ORACLES, QUERIES


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query(spark, sf, name):
    con = duckdb.connect()
    for t in ("documents", "embeddings", "pages"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    found, want = QUERIES[name](spark, sf), con.sql(ORACLES[name])
    names = sorted(want.columns)
    assert sorted(found.columns) == names
    at = [want.columns.index(c) for c in names]
    rows = sorted((tuple(r[k] for k in at) for r in want.fetchall()), key=str)
    assert sorted(map(tuple, found.select(*names).collect()), key=str) == rows

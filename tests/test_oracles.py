"""Every query with SQL gives the SQL's rows on the smallest tables."""

import duckdb
import pytest
from conftest import SF

from linseg.queries import ORACLES, QUERIES

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def db():
    con = duckdb.connect(config={"memory_limit": "3GB", "threads": 2})
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_same_rows(spark, db, name):
    got = QUERIES[name](spark, SF)
    cols = sorted(got.columns)
    rel = db.sql(ORACLES[name])
    assert sorted(rel.columns) == cols
    at = [rel.columns.index(c) for c in cols]
    want = sorted(repr(tuple(r[i] for i in at)) for r in rel.fetchall())
    assert sorted(repr(tuple(r[c] for c in cols)) for r in got.collect()) == want

"""Every query that has an oracle equals it on the smallest tables."""

import glob
import math
import os

import duckdb
import pytest

from lattice_pages.plans.queries import ORACLE_SQL, QUERIES


def rows(columns, data):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    key = lambda v: (v is None, repr(v) if not isinstance(v, (int, float)) else "", v if isinstance(v, (int, float)) and v is not None and not (isinstance(v, float) and math.isnan(v)) else 0)
    return sorted((tuple(r[i] for i in order) for r in data), key=lambda t: [key(v) for v in t])


@pytest.fixture(scope="module")
def duck(sf):
    db = duckdb.connect()
    for f in glob.glob(f"{sf}/*.parquet"):
        db.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    return db


@pytest.mark.parametrize("name", sorted(QUERIES))
def test_query(name, spark, sf, duck):
    got = QUERIES[name](spark, sf)
    if name not in ORACLE_SQL:
        assert got.count() > 0
        return
    want = duck.execute(ORACLE_SQL[name])
    columns = [d[0] for d in want.description]
    assert sorted(columns) == sorted(got.columns)
    assert rows(got.columns, got.collect()) == rows(columns, want.fetchall())

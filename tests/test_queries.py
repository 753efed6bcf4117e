"""Every core query against its SQL on the smallest tables."""

import decimal
import os

import duckdb
import pytest

from semimul.queries import ORACLES, QUERIES

DATA = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for f in os.listdir(DATA):
        con.execute(f"CREATE VIEW {f.split('.')[0]} AS SELECT * FROM '{DATA}/{f}'")
    return con


def text(v):
    if v is None or v != v:
        return "null"
    if isinstance(v, (float, decimal.Decimal)):
        return f"{v:.9g}"
    return str(v)


@pytest.mark.skipif(not os.path.isdir(DATA), reason="needs the given tables")
@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_matches_sql(spark, duck, name):
    got = QUERIES[name](spark, DATA)
    cur = duck.execute(ORACLES[name])
    columns = [c[0] for c in cur.description]
    assert sorted(got.columns) == sorted(columns)
    want = sorted("|".join(text(r[columns.index(c)]) for c in sorted(columns)) for r in cur.fetchall())
    assert sorted("|".join(text(r[c]) for c in sorted(columns)) for r in got.collect()) == want


@pytest.mark.skipif(not os.path.isdir(DATA), reason="needs the given tables")
def test_ranks_sum_to_one(spark):
    assert abs(sum(r.score for r in QUERIES["rank"](spark, DATA).collect()) - 1) < 1e-6

"""Every registered window-join query with an oracle, against DuckDB on the smallest tables."""

import duckdb
import pytest

from windowjoin.queries import experiments, joins, measures

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
ALL = joins.QUERIES | measures.QUERIES | experiments.QUERIES
SQL = joins.SQL | measures.SQL | experiments.SQL


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return con


def plain(x):
    if x is None or x != x:
        return None
    return round(float(x), 6) if isinstance(x, int | float) or type(x).__name__ in ("Decimal", "bool") else str(x)


@pytest.mark.parametrize("name", sorted(ALL))
def test_query(spark, duck, sf, name):
    df = ALL[name](spark, sf)
    cols = sorted(df.columns)
    got = sorted((tuple(plain(r[c]) for c in cols) for r in df.collect()), key=str)
    if name not in SQL:
        assert got
        return
    rel = duck.execute(SQL[name])
    names = [x[0] for x in rel.description]
    assert sorted(names) == cols
    at = [names.index(c) for c in cols]
    want = sorted((tuple(plain(r[i]) for i in at) for r in rel.fetchall()), key=str)
    assert got == want

"""Queries whose result must follow a given table: other rows, other result, and again that of the SQL."""

import duckdb
import pytest

from tests.test_oracles import plain
from windowjoin.queries import measures


@pytest.fixture(scope="module")
def other(sf, tmp_path_factory):
    """A third of the rows, and lower prices."""
    folder = tmp_path_factory.mktemp("tables")
    for name, what, where in (("orders", "*", "o_orderkey % 3 = 0"), ("events", "*", "event_id % 3 = 0"), ("lineitem", "* REPLACE (l_extendedprice / 64 AS l_extendedprice)", "l_orderkey % 3 = 0")):
        duckdb.execute(f"COPY (SELECT {what} FROM '{sf}/{name}.parquet' WHERE {where}) TO '{folder}/{name}.parquet' (FORMAT parquet)")
    return str(folder)


def rows(spark, name, folder):
    df = measures.QUERIES[name](spark, folder)
    cols = sorted(df.columns)
    con = duckdb.connect()
    for t in ("orders", "events", "lineitem"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{folder}/{t}.parquet'")
    want = con.execute(f"SELECT {', '.join(cols)} FROM ({measures.SQL[name]})").fetchall()
    key = lambda found: sorted((tuple(map(plain, r)) for r in found), key=str)
    assert key(df.select(cols).collect()) == key(want)
    return key(want)


@pytest.mark.parametrize("name", ["generated_uniform", "generated_narrow", "generated_normal", "generated_zipf", "generated_geometric", "convergence_generated", "metadata_overhead", "adjustment_bound", "index_bytes", "energy_ratio", "merge_cost_by_buffer", "python_source_tuples"])
def test_result_follows_the_table(spark, sf, other, name):
    assert rows(spark, name, sf) != rows(spark, name, other)

"""Registered queries of the tree engine against DuckDB on the smallest tables: all that need no long compression."""

import glob
import os

import duckdb
import pytest

from canopy import grammar_queries as G
from canopy import queries as Q
from canopy import table_queries as T

SF = "/root/testdata/sf0.001"
#: Queries that compress a workload of their own; two of them stand for the rest, which take minutes.
LONG = ("w1_roundtrip", "w2_roundtrip", "w2b_daily_roundtrip", "w3_roundtrip", "w4_roundtrip", "w5_roundtrip", "w6_roundtrip", "w8_roundtrip", "w8_recompress", "phase_stats", "node_access", "tree_heights", "x_", "w2_phase_one", "w5_phase_one", "baseline_")
QUERIES, SQL = {**Q.QUERIES, **T.QUERIES, **G.QUERIES}, {**Q.SQL, **T.SQL, **G.SQL}


def plain(x):
    return round(float(x), 6) if isinstance(x, float) else x


@pytest.mark.parametrize("name", sorted(x for x in SQL if not x.startswith(LONG)))
def test_query_equals_its_sql(spark, name):
    db = duckdb.connect()
    for f in glob.glob(f"{SF}/*.parquet"):
        db.sql(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    df = QUERIES[name](spark, SF)
    columns = sorted(df.columns)
    got = sorted(repr(tuple(map(plain, r))) for r in df.select(columns).collect())
    want = sorted(repr(tuple(map(plain, r))) for r in db.sql(SQL[name]).select(", ".join(f'"{c}"' for c in columns)).fetchall())
    assert got == want

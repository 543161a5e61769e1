"""The driver contract: queries run, names and columns agree with the SQL."""

import glob
import os

import duckdb
import pytest

import __spark_entry__ as entry

SOME = ["clusters_base", "labels_points", "rescue_missed", "hub_network", "matched_ratio_p4", "stream_daily", "clique_clusters"]


def test_flagship(spark):
    assert entry.entry(spark).select("r_tx", "r_ty").distinct().count() == 10


def test_every_sql_has_its_query():
    assert set(entry.oracle_sql()) <= set(entry.queries()) and len(entry.queries()) > 90


@pytest.mark.parametrize("name", SOME)
def test_sql_agrees(spark, tiny, name):
    con = duckdb.connect()
    for f in glob.glob(f"{tiny}/*.parquet"):
        con.sql(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    got = entry.queries()[name](spark, tiny)
    want = con.sql(entry.oracle_sql()[name])
    cols = sorted(got.columns)
    assert cols == sorted(want.columns)
    rows = [tuple(r[want.columns.index(c)] for c in cols) for r in want.fetchall()]
    assert sorted(map(repr, map(tuple, got.select(*cols).collect()))) == sorted(map(repr, rows))

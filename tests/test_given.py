"""Queries that once made up what they worked on: each reads a given table, and its rows are those of its SQL."""

import os

import duckdb
import pytest

from planepack.queries import ORACLES, QUERIES

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["partitions_15", "partitions_4140", "published_by_domain", "published_by_width", "published_table", "sql_choose", "sql_pack", "sql_set_partitions"])
def test_reads_a_given_table(spark, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        QUERIES[name](spark, "/nowhere").collect()
    con = duckdb.connect()
    for f in os.listdir(SF):
        con.execute(f"create view {f.removesuffix('.parquet')} as select * from '{SF}/{f}'")
    want = con.execute(ORACLES[name])
    columns = [c[0] for c in want.description]
    got = QUERIES[name](spark, SF).select(*columns).collect()
    key = lambda r: tuple(map(str, r))
    assert sorted(map(tuple, got), key=key) == sorted(want.fetchall(), key=key)

import duckdb

from planepack.relops import RELOPS


def test_best_of_equal_values_is_the_first(spark, tmp_path):
    rows = [(i, t, v) for i, (t, v) in enumerate([("a", 5.0), ("a", 9.0), ("a", 9.0), ("a", 5.0), ("a", None), ("b", None), ("c", 1.0), ("c", 1.0), ("c", -0.0), ("c", 0.0), ("d", float("nan")), ("d", 2.0), ("d", float("nan"))])]
    rows.append((None, "a", 99.0))
    spark.createDataFrame(rows, "event_id long, event_type string, value double").coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    query, sql = RELOPS["agg_best_by"]
    con = duckdb.connect()
    con.execute(f"create view events as select * from '{tmp_path}/events.parquet/*.parquet'")
    got = {r.event_type: (r.top, r.low, r.big) for r in query(spark, str(tmp_path)).collect()}
    assert got == {r[0]: tuple(r[1:]) for r in con.execute(sql).fetchall()}
    assert got["a"][:2] == (1, 0) and got["c"][:2] == (6, 8)

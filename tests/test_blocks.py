import numpy as np
import pytest
from pyspark.sql import functions as F

from planepack import blocks, container, datasource, pipeline
from planepack.features import feature_table, plane_hist, plane_hist_sql

DDL = "dataset string, width int, k1 long, k2 long, k3 long, k4 long, k5 long, bits long"


def words(spark, rows):
    """(dataset, width, k1, bits) rows with the number of the row as the second key."""
    return spark.createDataFrame([(d, w, k, i, 0, 0, 0, b) for i, (d, w, k, b) in enumerate(rows)], DDL)


def back(df):
    return [(r.dataset, r.block_id, r.pos, r.bits) for r in blocks.words_of_blocks(df).orderBy("dataset", "block_id", "pos").collect()]


def expected(rows, block_bytes):
    out = []
    for ds in sorted({r[0] for r in rows}):
        mine = [(k, i, w, b) for i, (d, w, k, b) in enumerate(rows) if d == ds]
        mine.sort(key=lambda x: (x[0] is not None, x[0] or 0, x[1]))
        per = block_bytes // mine[0][2]
        out += [(ds, n // per, n % per, b) for n, (_, _, _, b) in enumerate(mine)]
    return out


@pytest.mark.parametrize("piece", [64, 1 << 20])
def test_order_nulls_skew_and_tails(spark, monkeypatch, piece):
    monkeypatch.setattr(blocks, "PIECE_BYTES", piece)
    rng = np.random.default_rng(1)
    rows = [("a", 8, None if i % 10 == 0 else 7 if i % 3 else int(rng.integers(1000)), int(v)) for i, v in enumerate(rng.integers(-(1 << 62), 1 << 62, 333))]
    rows += [("one", 4, 5, -3), ("exact", 4, 1, 0)] + [("exact", 4, i, i) for i in range(2, 17)]
    rows += [("nulls", 8, i, None if i % 7 == 0 else i * i) for i in range(100)] + [("void", 8, i, None) for i in range(9)]
    assert back(blocks.blocks(words(spark, rows), 64)) == expected(rows, 64)
    both = blocks.ranked(words(spark, rows), 64).orderBy("dataset", "rn").collect()
    assert [(r.dataset, r.block_id, r.pos, r.bits) for r in both] == expected(rows, 64)
    # through a container, nulls and all
    assert back(pipeline.decompress_blocks(pipeline.compress(blocks.blocks(words(spark, rows), 64)))) == expected(rows, 64)


def test_sizes_from_the_same_pieces(spark):
    rows = [("a", 8, i, i) for i in range(1000)]
    pieces = blocks.gathered(words(spark, rows), 512)
    for size in (8, 64, 512):
        assert back(blocks.cut(pieces, size)) == expected(rows, size)


def test_blocks_larger_than_the_ends_are_refused(spark, monkeypatch):
    monkeypatch.setattr(blocks, "PIECE_BYTES", 512)
    with pytest.raises(Exception, match="larger than the ends"):
        blocks.cut(blocks.gathered(words(spark, [("a", 8, i, i) for i in range(1000)]), 64), 4096).collect()


def test_empty_and_repeated_keys(spark):
    empty = words(spark, [("a", 8, 1, 1)]).filter("k1 > 1")
    assert blocks.blocks(empty, 64).collect() == [] and blocks.ranked(empty).collect() == []
    twice = words(spark, [("a", 8, 1, 1), ("a", 8, 2, 5)]).withColumn("k2", F.lit(0)).withColumn("k1", F.lit(1))
    with pytest.raises(ValueError, match="not unique"):
        blocks.blocks(twice, 64)
    assert [x[3] for x in back(blocks.blocks(twice, 64, unique=False))] == [1, 5]
    nulls = twice.withColumn("k1", F.lit(None).cast("long"))
    with pytest.raises(ValueError, match="not unique"):
        blocks.blocks(nulls, 64)


def test_repeated_keys_at_the_edges_of_tasks(spark):
    """Two words of one key, and more ranges than words: the repeat is noticed although a range could end between them."""
    pairs = words(spark, [("a", 8, 1, i) for i in range(2)]).withColumn("k2", F.lit(0))
    adaptive = spark.conf.get("spark.sql.adaptive.enabled")
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        with pytest.raises(ValueError, match="not unique"):
            blocks.blocks(pairs, 64)
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", adaptive)


def test_samples(spark):
    ids = spark.range(1000).select(F.lit("a").alias("dataset"), F.col("id").alias("block_id"))
    for share, n in ((0.04, 40), (0.25, 250), (0.3, 300)):
        got = sorted(r.block_id for r in blocks.sample_blocks(ids, share).collect())
        assert len(got) == n and got[0] == 0
        assert [r.block_id for r in blocks.sample_blocks(ids, share, "prefix").orderBy("block_id").collect()] == list(range(n))


def test_partial_statistics_equal_plain_ones(spark):
    rng = np.random.default_rng(2)
    rows = [("a", 4, i, int(v)) for i, v in enumerate(rng.integers(-9000, 9000, 500))] + [("c", 8, i, 1) for i in range(40)]
    df = words(spark, rows)
    for by in ((), ("k2",)):
        assert sorted(map(tuple, plane_hist(df, *by).collect())) == sorted(map(tuple, plane_hist_sql(df, *by).select(*plane_hist(df, *by).columns).collect()))
    got = {(r.dataset, r.plane): r for r in feature_table(blocks.blocks(df, 256)).collect()}
    x = np.array([b for d, _, _, b in rows if d == "a"], "<i4")
    h = []
    for i in range(0, 500, 64):
        c = np.unique(x[i : i + 64].view(np.uint8).reshape(-1, 4)[:, 0], return_counts=True)[1]
        h.append(round(float(np.log2(c.sum()) - (c * np.log2(c)).sum() / c.sum()), 6))
    r = got[("a", 3)]
    assert np.allclose([r.h_avg, r.h_std, r.h_max, r.h_min], [np.mean(h), np.std(h, ddof=1), max(h), min(h)])
    assert sum(r.hist) == 500 and got[("c", 0)].h_std == 0.0


def test_narrow_compression(spark):
    b = spark.createDataFrame([("a", 4, 0, 2, 0, None, bytearray(8))], blocks._BLOCK_DDL)
    plan = pipeline.compress_blocks(b, {"a": [[0], [1, 2, 3]]})._jdf.queryExecution().toString()
    assert "Exchange" not in plan


def test_container_pruning_and_unwhole_files(spark, tmp_path):
    df = words(spark, [("x y/z", 8, i, i) for i in range(300)])
    path = str(tmp_path / "c")
    container.write_container(pipeline.compress(blocks.blocks(df, 80)), path)
    got = container.read_range(spark, path, "x y/z", 95, 205, 80, 8).orderBy("rn").collect()
    assert [r.bits for r in got] == list(range(95, 205))
    datasource.register(spark)
    t = spark.read.format("planepack").option("path", path).load().filter("dataset = 'x y/z' and block_id = 3")
    assert sorted(r.bits for r in t.collect()) == list(range(30, 40))
    (tmp_path / "odd").mkdir()
    (tmp_path / "odd" / "f.bin").write_bytes(b"12345")
    with pytest.raises(ValueError, match="whole words"):
        datasource.read_raw_words(spark, str(tmp_path / "odd"), "f32")

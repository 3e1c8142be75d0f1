"""Sizes of the studies against the tools themselves, on arrays read without Spark."""

import bz2
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest

from planepack import ablation, cluster, pipeline, queries, studies
from planepack.codecs import CODECS

SF = "/root/testdata/sf0.001"
TOOLS = {"zstd": lambda b: pa.compress(b, "zstd", asbytes=True), "zlib": lambda b: zlib.compress(b, 6), "bzip2": lambda b: bz2.compress(b, 9), "snappy": lambda b: pa.compress(b, "snappy", asbytes=True), "lz4": lambda b: pa.compress(b, "lz4_raw", asbytes=True)}


def column(name):
    if name == "TS32-value":
        t = pq.read_table(f"{SF}/events.parquet").sort_by("event_id")
        return t["value"].to_numpy().astype("<f4")
    t = pq.read_table(f"{SF}/part.parquet").sort_by("p_partkey")
    return t["p_size"].to_numpy().astype("<i4")


def cut(x):
    per = studies.BLOCK // x.itemsize
    return [x[i : i + per] for i in range(0, len(x), per)]


@pytest.mark.parametrize("name", ["TS32-value", "INT32-size"])
def test_ratios_of_every_tool(spark, name):
    b = studies._blocks(spark, SF, name)
    (part,) = pipeline.fit(b).values()
    got = {(r.codec, r.variant): r for r in ablation.split_job(ablation.measure(b, ablation.both(list(TOOLS), {name: part})), "codec", "variant").collect()}
    x = column(name)
    for t, f in TOOLS.items():
        assert got[(t, "standard")].enc == sum(len(f(p.tobytes())) for p in cut(x))
        split = 0
        for p in cut(x):
            planes = p.view(np.uint8).reshape(-1, 4)[:, ::-1]
            split += sum(len(f(np.ascontiguousarray(planes[:, g].T).tobytes())) for g in part)
        assert got[(t, "clustered")].enc == split and got[(t, "clustered")].exact


def test_whole_file_streams_equal_one_call(spark):
    got = {r.codec: r.enc for r in queries.QUERIES["whole_file_table"](spark, SF).filter("dataset = 'TS32-value'").collect()}
    x = column("TS32-value").tobytes()
    assert got["zlib"] == len(zlib.compress(x, 6)) and got["bzip2"] == len(bz2.compress(x, 9))
    assert abs(got["zstd"] - len(TOOLS["zstd"](x))) < 32 and abs(got["lz4"] - len(TOOLS["lz4"](x))) < 64


def test_search_finds_the_least(spark):
    b = studies._blocks(spark, SF, "TS32-value")
    got = {(r.packing, r.partition): r.enc for r in ablation.exhaustive(b, 4).collect()}
    x = column("TS32-value")
    assert len(got) == 30
    for c in cluster.set_partitions(4):
        want = 0
        for p in cut(x):
            planes = p.view(np.uint8).reshape(-1, 4)[:, ::-1]
            want += sum(len(TOOLS["zstd"](np.ascontiguousarray(planes[:, g].T).tobytes())) for g in c)
        assert got[("byte", str(c))] == want
    least = pipeline.fit(b, pipeline.PlanSpec(score="measured", sample=1.0))["TS32-value"]
    tried = [str(c) for c in cluster.linkage(studies.features.collect_features(b)["TS32-value"])]
    assert got[("byte", str(least))] == min(got[("byte", c)] for c in tried)


def test_rules_of_the_choice():
    x = np.array([[0.0], [1.0], [10.0], [12.0]])
    assert cluster.choose_partition(x, "davies_bouldin", degenerate="paper") == [[0, 1], [2], [3]]
    assert cluster.choose_partition(np.zeros((4, 3)), "silhouette") == cluster.choose_partition(np.zeros((4, 3)), "silhouette", degenerate="strict")
    assert cluster.is_partition(cluster.choose_partition(x, "gap_one_se"), 4)
    assert cluster.choose_partition(np.random.default_rng(0).random((2, 3)), "gap_one_se") == [[0], [1]]


def test_two_dimensional_prediction_wins_on_rows():
    i, j = np.mgrid[0:64, 0:64]
    data = ((i * 3.0 + j * 5.0) + 1000).astype("<f4").tobytes()
    one, two = (CODECS[c].encode(data, 4, None) for c in ("predictive", "predictive-2d"))
    assert len(two) < len(one) and CODECS["predictive-2d"].decode(two, 4, len(data)) == data
